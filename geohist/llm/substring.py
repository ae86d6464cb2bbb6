"""Repeated word windows across documents: a count-min prefilter from merged partition sketches, then exact grouping."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from geohist.llm.common import Scratch, as_strings, byte_view, row_id, run_hashes, steps, word_hashes, word_spans

#: Words of a window; bounds in bits of the prefilter's table for each row of the sketch.
WINDOW, LEAST_BITS, MOST_BITS = 13, 1 << 20, 1 << 30
#: The sketch has ROWS rows of 2^32 cells, kept as sorted lists in 256 slices each; a partial sketch is written after so many windows.
ROWS, SLICES, PARTIAL = 2, 256, 3_000_000
#: Candidate windows that a task folds at a time.
FOLD = 1_000_000
_LAST = 2**63 - 1


def _windows(texts: pa.Array, size: int):
    """Both hashes of every window, the row it starts in and the word it starts at."""
    raw, off = byte_view(texts)
    one, two, _, _, word = word_hashes(raw, off, lower=False)
    count = np.maximum(np.diff(word) - size + 1, 0)
    total = int(count.sum())
    row = np.repeat(np.arange(len(texts)), count)
    at = np.arange(total) - np.repeat(np.cumsum(count) - count, count)
    pick = np.repeat(word[:-1], count) + at
    return run_hashes(one, size, 1)[pick], lambda: run_hashes(two, size, 2)[pick], row, at


def _cell(h: np.ndarray, row: int) -> np.ndarray:
    """The cell of a window in a row of the sketch: 32 bits of its first hash for each of the two rows."""
    return (h >> np.uint64(32) if row == 0 else h & np.uint64(0xFFFFFFFF)).astype(np.uint32)


def partial_sketches(rows: DataFrame, size: int = WINDOW) -> DataFrame:
    """(slice, once, more, counts): sketch cells that a part of a task's windows hits once, and hits more often with their counts, by row of the sketch and slice."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []

        def emit() -> pa.RecordBatch:
            h = np.concatenate(held)
            held.clear()
            first = (np.arange(SLICES, dtype=np.uint64) << np.uint64(24)).astype(np.uint32)
            out: list[list] = [[], [], [], []]
            for row in range(ROWS):
                cells, n = np.unique(_cell(h, row), return_counts=True)
                one = n == 1
                lists = (cells[one], cells[~one])
                counts = np.minimum(n[~one], 255).astype(np.uint8)
                cut = [np.append(np.searchsorted(c, first), len(c)) for c in lists]
                for s in range(SLICES):
                    a, b = lists[0][cut[0][s] : cut[0][s + 1]], lists[1][cut[1][s] : cut[1][s + 1]]
                    if len(a) or len(b):
                        # a sorted list of 24-bit cells: 256 counts by the high byte, then the low 16 bits of each
                        high = np.bincount((a >> 16) & 255, minlength=256).astype("<u4")
                        out[0].append(row * SLICES + s)
                        out[1].append(high.tobytes() + (a & 0xFFFF).astype("<u2").tobytes())
                        out[2].append((b & 0xFFFFFF).astype("<u4").tobytes())
                        out[3].append(counts[cut[1][s] : cut[1][s + 1]].tobytes())
            return pa.RecordBatch.from_arrays([pa.array(out[0], pa.int32()), *(pa.array(x, pa.binary()) for x in out[1:])], ["slice", "once", "more", "counts"])

        for b in batches:
            texts = as_strings(b.column(0))
            for lo, hi in steps(texts):
                held.append(_windows(texts.slice(lo, hi - lo), size)[0])
                if sum(map(len, held)) >= PARTIAL:
                    yield emit()
        if held:
            yield emit()

    return rows.select("text").mapInArrow(run, "slice int, once binary, more binary, counts binary")


def merged_sketch(partial: DataFrame) -> DataFrame:
    """(slice, repeated): cells of the summed sketch that count 2 or more. One slice of one row is in memory at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, cells = None, np.zeros(1 << 24, np.uint8)

        def done() -> pa.RecordBatch:
            repeated = np.flatnonzero(cells >= 2).astype("<u4").tobytes()
            cells[:] = 0
            return pa.RecordBatch.from_arrays([pa.array([now], pa.int32()), pa.array([repeated], pa.binary())], ["slice", "repeated"])

        for b in batches:
            for s, once, more, counts in zip(b.column(0).to_pylist(), b.column(1), b.column(2), b.column(3)):
                if now is not None and s != now:
                    yield done()
                now = s
                buf = once.as_buffer()
                high = np.frombuffer(buf, "<u4", 256)
                at = np.repeat(np.arange(256, dtype=np.uint32) << 16, high) | np.frombuffer(buf, "<u2", offset=1024)
                cells[at] = np.where(cells[at] < 255, cells[at] + 1, 255)
                at, n = np.frombuffer(more.as_buffer(), "<u4"), np.frombuffer(counts.as_buffer(), np.uint8)
                cells[at] = np.minimum(cells[at].astype(np.uint16) + n, 255)
        if now is not None:
            yield done()

    return partial.repartition("slice").sortWithinPartitions("slice").mapInArrow(run, "slice int, repeated binary")


class Prefilter:
    """For each row of the sketch a table of bits, set for cells that count 2 or more; its size is chosen from their number, within fixed bounds.

    A window's estimate is the least of its cells, so it says repeated only where every row does.
    """

    def __init__(self, merged: DataFrame, most_bits: int = MOST_BITS):
        row = F.floor(F.col("slice") / SLICES).cast("int")
        n = {r["row"]: r["n"] // 4 for r in merged.groupBy(row.alias("row")).agg(F.sum(F.octet_length("repeated")).alias("n")).collect()}  # a row for each row of the sketch
        self.shift, self.bits = zip(*(self._fold(merged.where(row == i), n.get(i, 0), most_bits) for i in range(ROWS)))

    @staticmethod
    def _fold(lists: DataFrame, cells: int, most_bits: int) -> tuple[int, np.ndarray]:
        log = min(max(LEAST_BITS, 1 << (16 * cells).bit_length()), most_bits).bit_length() - 1
        shift, per = 32 - log, 1 << (log - 11)  # bytes of a slice

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for s, x in zip(b.column(0).to_pylist(), b.column(1)):
                    on = np.zeros(per * 8, np.uint8)
                    on[np.frombuffer(x.as_buffer(), "<u4") >> shift] = 1
                    yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([np.packbits(on, bitorder="little").tobytes()], pa.binary())], ["slice", "cells"])

        bits = np.zeros(per * SLICES, np.uint8)
        for r in lists.mapInArrow(run, "slice int, cells binary").toLocalIterator():
            s = r["slice"] % SLICES
            bits[s * per : (s + 1) * per] = np.frombuffer(bytes(r["cells"]), np.uint8)
        return shift, bits

    def test(self, h: np.ndarray) -> np.ndarray:
        found = np.ones(len(h), bool)
        for row in range(ROWS):
            at = _cell(h, row) >> np.uint32(self.shift[row])
            found &= (self.bits[row][at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1
        return found


def _folded(h1: np.ndarray, h2: np.ndarray, doc: np.ndarray, row: np.ndarray, at: np.ndarray) -> pa.RecordBatch:
    """Candidates of a part of a task: those of the smallest id for each window, one row for each window and text, and the others, which are repeats for sure, one row for each text."""
    order = np.lexsort((row, h2, h1))  # stable: places ascend
    a, b = h1[order], h2[order]
    new = np.r_[True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])]
    lead = np.flatnonzero(new)
    least = np.repeat(np.minimum.reduceat(doc[order], lead), np.diff(np.append(lead, len(order))))
    sure = doc[order] > least
    new[1:] |= row[order][1:] != row[order][:-1]
    own = order[~sure]
    open_ = order[new & ~sure]
    own_at = np.flatnonzero(new[~sure])
    told = order[sure]
    told = told[np.lexsort((at[told], row[told]))]
    first = np.flatnonzero(np.r_[True, row[told][1:] != row[told][:-1]]) if len(told) else np.zeros(0, np.int64)
    m = len(first)
    off = np.concatenate([own_at, len(own) + first, [len(order)]])
    starts = pa.ListArray.from_arrays(pa.array(off.astype(np.int32)), pa.array(np.concatenate([at[own], at[told]]).astype(np.int32)))
    one = told[first]
    none = pa.nulls(m, pa.int64())
    join = lambda x, y: pa.concat_arrays([pa.array(x), y])
    # Rows that are sure meet no others: their own number and no second hash stand for a window.
    return pa.RecordBatch.from_arrays([pa.array(np.concatenate([h1[open_].view(np.int64), row[one]])), join(h2[open_].view(np.int64), none), join(doc[open_], none), pa.array(np.concatenate([row[open_], row[one]])), starts], ["h1", "h2", "doc_id", "row", "starts"])


def candidate_windows(rows: DataFrame, prefilter: Prefilter, size: int = WINDOW) -> DataFrame:
    """(h1, h2, doc_id, row, starts) of windows whose estimate says repeated, folded in each task; 128 bits stand for a window's words.

    Where one task holds a window in several documents, only the smallest of them can be its first; the others are
    repeats, and leave with h2 and doc_id null. So a window takes one row a fold, however many documents hold it.
    """
    sent = rows.sparkSession.sparkContext.broadcast(prefilter)  # of bounded size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f, held = sent.value, []
        for b in batches:
            texts = as_strings(b.column(2))
            own, doc = b.column(0).to_numpy(), b.column(1).to_numpy()
            for lo, hi in steps(texts):
                h1, second, row, at = _windows(texts.slice(lo, hi - lo), size)
                keep = np.flatnonzero(f.test(h1))
                if len(keep):
                    row = row[keep] + lo
                    held.append((h1[keep], second()[keep], doc[row], own[row], at[keep]))
                    if sum(len(x[0]) for x in held) >= FOLD:
                        yield _folded(*map(np.concatenate, zip(*held)))
                        held = []
        if held:
            yield _folded(*map(np.concatenate, zip(*held)))

    return rows.select("row", F.coalesce("doc_id", F.lit(_LAST)).alias("doc_id"), "text").mapInArrow(run, "h1 long, h2 long, doc_id long, row long, starts array<int>")


def repeated_windows(rows: DataFrame, size: int = WINDOW) -> DataFrame:
    """(row, starts) of the windows whose words also start in a document of smaller id, exactly; a row may come several times."""
    scratch = Scratch(rows.sparkSession)
    prefilter = Prefilter(scratch.keep(merged_sketch(partial_sketches(rows, size))))
    scratch.drop()  # its bits are here now, and the partial sketches were the largest shuffle
    found = candidate_windows(rows, prefilter, size)
    least = F.min("doc_id").over(W.partitionBy("h1", "h2"))
    return found.withColumn("least", least).where("h2 is null or least < doc_id").select("row", "starts")


_OUT = "row long, doc_id long, n_words long, n_removed long, kept_sha256 string"


def _cleaned(size: int, with_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts, starts = as_strings(b.column(2)), b.column(3)
            for lo, hi in steps(texts):
                part = texts.slice(lo, hi - lo)
                raw, off = byte_view(part)
                begin, stop, word = word_spans(raw, off)
                cols: list[list] = [[], [], [], []]
                data = raw.tobytes()
                for i in range(hi - lo):
                    a, z = int(word[i]), int(word[i + 1])
                    at = starts[lo + i].values
                    keep = np.ones(z - a, bool)
                    if at is not None and len(at):
                        at = at.to_numpy()
                        delta = np.bincount(at, minlength=z - a + 1) - np.bincount(at + size, minlength=z - a + 1)[: z - a + 1]
                        keep = np.cumsum(delta)[: z - a] == 0
                    kept = a + np.flatnonzero(keep)
                    text = b" ".join([data[x:y] for x, y in zip(begin[kept].tolist(), stop[kept].tolist())])
                    cols[0].append(z - a)
                    cols[1].append(z - a - len(kept))
                    cols[2].append(hashlib.sha256(text).hexdigest())
                    if with_text:
                        cols[3].append(text.decode("utf-8", "replace"))
                arrays = [b.column(0).slice(lo, hi - lo), b.column(1).slice(lo, hi - lo), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.string())]
                yield pa.RecordBatch.from_arrays(arrays + [pa.array(cols[3], pa.string())] * with_text, ["row", "doc_id", "n_words", "n_removed", "kept_sha256"] + ["kept_text"] * with_text)

    return run


def remove_repeats(docs: DataFrame, size: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False, row_col: str | None = None) -> DataFrame:
    """One row for each row of docs: row, doc_id, n_words, n_removed, kept_sha256 (and kept_text: kept words joined by one space).

    A word goes if some window of `size` consecutive words that covers it also starts in a document with a smaller
    id; windows are judged on the input. Null texts have no words; a null id counts as the largest; rows that
    share an id do not remove each other's words. Texts shorter than a window keep all words.
    """
    rows = docs.select((F.col(row_col) if row_col else row_id()).alias("row"), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    starts = repeated_windows(rows, size).groupBy("row").agg(F.flatten(F.collect_list("starts")).alias("starts"))
    return rows.join(starts, "row", "left").select("row", "doc_id", "text", "starts").mapInArrow(_cleaned(size, with_text), _OUT + ", kept_text string" * with_text)


def op5_substring_dedup(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop("row")
