"""Token packing by multiway differencing: windows of near-equal fill, every token in exactly one piece."""

from __future__ import annotations

import heapq
import json
import zlib
from bisect import insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geohist.llm.common import as_strings, steps

#: Pieces that one differencing run spreads over its windows, and the pieces a full window holds at least: what a
#: document has beyond whole sequences is cut to a PIECES-th of the capacity, so that windows can come out near equal.
GROUP_PIECES, PIECES = 4096, 4


def _join(a: list, b: list, ways: int, meet) -> list:
    """Two partial partitions as one: (sum, node) of their filled ways, ascending. The fullest ways of one meet the emptiest of the other."""
    if len(a) < len(b):
        a, b = b, a
    overlap = len(a) + len(b) - ways
    if len(b) == 1:
        if overlap > 0:
            first = a.pop(0)
            insort(a, (first[0] + b[0][0], meet(first[1], b[0][1])))
        else:
            insort(a, b[0])
        return a
    if overlap <= 0:
        return sorted(a + b)
    # The largest of b take the empty ways of a; the rest, descending, meet a's ways from the emptiest up.
    both = [(x + y, meet(i, j)) for (x, i), (y, j) in zip(a, b[overlap - 1 :: -1])]
    return sorted(both + a[overlap:] + b[overlap:])


def difference(sizes: np.ndarray, ways: int) -> np.ndarray:
    """Multiway differencing: the way of each item so that the sums of `ways` ways are near equal.

    Each item starts as a partial partition with one filled way. The two partial partitions of largest spread
    merge, fullest way onto emptiest, until one is left. Ties fall to the lower item, so results repeat.
    """
    n = len(sizes)
    if ways <= 1 or n == 0:
        return np.zeros(n, np.int64)
    left, right = list(range(n)), [-1] * n  # the two that met in a node; items stand for themselves

    def meet(i: int, j: int) -> int:
        left.append(i)
        right.append(j)
        return len(left) - 1

    heap = [(-x, i, [(x, i)]) for i, x in enumerate(sizes.tolist())]
    heapq.heapify(heap)
    serial = n
    while len(heap) > 1:
        a, b = heapq.heappop(heap)[2], heapq.heappop(heap)[2]
        sums = _join(a, b, ways, meet)
        heapq.heappush(heap, ((sums[0][0] if len(sums) == ways else 0) - sums[-1][0], serial, sums))
        serial += 1
    way = np.zeros(n, np.int64)
    for w, (_, top) in enumerate(heap[0][2]):
        stack = [top]
        while stack:
            x = stack.pop()
            if x < n:
                way[x] = w
            else:
                stack += [left[x], right[x]]
    return way


def spread(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, int]:
    """Windows of the items and their number: the least that could do, more whenever a window is over full (a 256th of them, one at least)."""
    ways = max(1, -(-int(sizes.sum()) // capacity))
    while True:
        way = difference(sizes, ways)
        if np.bincount(way, weights=sizes, minlength=ways).max(initial=0) <= capacity:
            return way, ways
        ways += max(1, ways // 256)


#: A chunk of Latin letters, then ASCII marks (no apostrophe, which may open a contraction).
_LATIN = r"[A-Za-z\x{C0}-\x{D6}\x{D8}-\x{F6}\x{F8}-\x{FF}\x{152}\x{153}]+"
_MARKS = "!\"#$%&()*+,-./:;<=>?@[\\]^_`{|}~"
#: What cuts such a chunk between letters and marks, and has no regard to capitals.
_CUTTER = {"type": "Split", "pattern": {"Regex": r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"}, "behavior": "Removed", "invert": True}


def cuts_at_marks(path: str) -> bool:
    """Whether the file's tokenizer normalises by NFC and lower case only and then encodes runs of letters and of marks apart."""
    with open(path, encoding="utf-8") as f:
        file = json.load(f)
    norm, pre = ((file.get(k) or {}).get(v, []) for k, v in (("normalizer", "normalizers"), ("pre_tokenizer", "pretokenizers")))
    return [x["type"] for x in norm] == ["NFC", "Replace", "Lowercase"] and norm[1].get("pattern") == {"Regex": "\\s+"} and pre[:1] == [_CUTTER] and [(x["type"], x.get("add_prefix_space"), x.get("use_regex")) for x in pre[1:]] == [("ByteLevel", False, False)]


def letters_and_marks(chunks: pa.Array) -> tuple[pa.Array, pa.Array]:
    """Lower-case letters and the marks behind them, of chunks that are only these; any other chunk as it is, and an empty text."""
    letters = pc.utf8_rtrim(chunks, characters=_MARKS)
    simple = pc.match_substring_regex(letters, f"^{_LATIN}$")
    marks = pc.replace_substring_regex(pc.if_else(simple, chunks, ""), f"^{_LATIN}", "")
    return pc.if_else(simple, pc.utf8_lower(letters), chunks), marks


class ChunkEncoder:
    """Ids of whole texts for tokenizers that drop white space: each distinct space-free chunk is encoded once.

    Where the tokenizer encodes letters and marks apart, so are they learnt: `Word.` and `word` need one entry and that of `.`.
    New chunks go to the library as one text with an added token between them, at which it cuts before anything
    else; chunks that hold an added token themselves go alone. Ids of known chunks lie end to end in one array.
    """

    def __init__(self, path: str, limit: int = 400_000, most_chars: int = 32_000_000):
        from tokenizers import Tokenizer

        self.tokenizer, self.limit, self.most_chars = Tokenizer.from_file(path), limit, most_chars
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        added = {t.content: i for i, t in self.tokenizer.get_added_tokens_decoder().items() if t.special and not (t.lstrip or t.rstrip or t.single_word or t.normalized)}
        self.added = tuple(t.content for t in self.tokenizer.get_added_tokens_decoder().values())
        self.mark, self.mark_id = next(iter(added.items()), (None, -1))
        self.apart = cuts_at_marks(path)
        self._forget()

    def _forget(self) -> None:
        self.known: dict[str, int] = {}
        self.chars = 0
        self.flat, self.size = np.zeros(0, np.uint32), np.zeros(0, np.int64)

    def _learn(self, new: list[str]) -> None:
        whole = " ".join(new)
        there = [t for t in self.added if t in whole]
        odd = new if not self.mark else [w for w in new if any(t in w for t in there)] if there else []
        plain = [w for w in new if w not in alone] if (alone := set(odd)) else new
        flat, size = [self.flat], [self.size]
        for lo in range(0, len(plain), 20_000):
            part = plain[lo : lo + 20_000]
            ids = np.array(self.tokenizer.encode_batch_fast([self.mark.join(part)], add_special_tokens=False)[0].ids, np.uint32)
            cut = np.append(np.flatnonzero(ids == self.mark_id), len(ids))
            size.append(np.diff(np.concatenate([[-1], cut])) - 1)
            flat.append(ids[ids != self.mark_id])
        for w in odd:
            ids = self.tokenizer.encode(w, add_special_tokens=False).ids
            size.append(np.array([len(ids)], np.int64))
            flat.append(np.array(ids, np.uint32))
        self.chars += len(whole)
        self.known.update(zip(plain + odd, range(len(self.known), len(self.known) + len(new))))
        self.flat, self.size = np.concatenate(flat), np.concatenate(size)

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts laid end to end (uint32) and n+1 offsets."""
        lists = pc.ascii_split_whitespace(texts)
        ends = np.concatenate([[0], np.cumsum(pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64))])
        coded = lists.flatten().dictionary_encode()
        chunks = coded.dictionary
        sides = letters_and_marks(chunks) if self.apart else (chunks,)
        parts = pa.concat_arrays(sides).dictionary_encode()
        words = parts.dictionary.to_pylist()
        if len(self.known) > self.limit or self.chars > self.most_chars:
            self._forget()
        if new := [w for w in words if w not in self.known]:
            self._learn(new)
        index = np.fromiter(map(self.known.__getitem__, words), np.int64, len(words))[parts.indices.to_numpy(zero_copy_only=False)]
        index = index.reshape(len(sides), -1).T  # the parts of each chunk
        flat, _ = self._laid(self.flat, np.cumsum(self.size) - self.size, self.size, index.ravel())
        size = self.size[index].sum(axis=1)
        ids, at = self._laid(flat, np.cumsum(size) - size, size, coded.indices.to_numpy(zero_copy_only=False))
        return ids, at[ends]

    @staticmethod
    def _laid(flat: np.ndarray, first: np.ndarray, size: np.ndarray, index: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Runs of flat in the order of index, end to end, and their n+1 offsets."""
        n = size[index]
        at = np.concatenate([[0], np.cumsum(n)])
        return flat[np.repeat(first[index] - at[:-1], n) + np.arange(at[-1])], at


_ENCODERS: dict[str, ChunkEncoder] = {}


def chunk_encoder(path: str) -> ChunkEncoder:
    """The worker's encoder of a file: what it knows stays from task to task."""
    if path not in _ENCODERS:
        _ENCODERS.clear()
        _ENCODERS[path] = ChunkEncoder(path)
    return _ENCODERS[path]


_SCHEMA = "row_id long, doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def _pack(path: str, capacity: int, end_id: int, group: int, with_ids: bool):
    names = [x.split()[0] for x in _SCHEMA.split(", ")]
    most = max(1, capacity // PIECES)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, next_id = chunk_encoder(path), TaskContext.get().partitionId() << 40
        whole, rest = [], []  # (row, doc, start, ids, doc tokens)

        def emit(pieces: list, seq: np.ndarray, offset: np.ndarray) -> pa.RecordBatch:
            cols = [pa.array(c, pa.int64()) for c in ([p[0] for p in pieces], [p[1] for p in pieces], [p[2] for p in pieces], [len(p[3]) for p in pieces], [zlib.crc32(p[3]) for p in pieces], [p[4] for p in pieces], seq, offset)]
            if with_ids:
                cols.append(pa.array([p[3].astype(np.int32) for p in pieces], pa.list_(pa.int32())))
            return pa.RecordBatch.from_arrays(cols, names + ["ids"] * with_ids)

        def joined(pieces: list, way: np.ndarray) -> tuple[list, np.ndarray]:
            """Pieces in order of their window, those that follow each other in a document and fell into one window as one again."""
            out, own = [], []
            for i in np.argsort(way, kind="stable").tolist():
                row, doc, start, ids, total = pieces[i]
                if out and own[-1] == way[i] and out[-1][0] == row and out[-1][2] + len(out[-1][3]) == start:
                    out[-1] = (row, doc, out[-1][2], np.concatenate([out[-1][3], ids]), total)
                else:
                    out.append(pieces[i])
                    own.append(way[i])
            return out, np.array(own, np.int64)

        def flush() -> Iterator[pa.RecordBatch]:
            nonlocal whole, rest, next_id
            if whole:
                yield emit(whole, next_id + np.arange(len(whole)), np.zeros(len(whole), np.int64))
                next_id += len(whole)
            if rest:
                way, ways = spread(np.array([len(p[3]) for p in rest], np.int64), capacity)
                pieces, w = joined(rest, way)
                n = np.array([len(p[3]) for p in pieces], np.int64)
                before = np.cumsum(n) - n
                lead = np.flatnonzero(np.r_[True, w[1:] != w[:-1]])
                base = np.zeros(ways, np.int64)
                base[w[lead]] = before[lead]
                yield emit(pieces, next_id + w, before - base[w])
                next_id += ways
            whole, rest = [], []

        for b in batches:
            texts = as_strings(b.column(2))
            row, doc = b.column(0).to_pylist(), b.column(1).to_pylist()
            for lo, hi in steps(texts, 8_000_000):
                ids, off = encoder.encode(texts.slice(lo, hi - lo))
                for i in range(hi - lo):
                    own = np.append(ids[off[i] : off[i + 1]], np.uint32(end_id)).astype("<u4")
                    total = len(own)
                    full = total - total % capacity
                    whole += [(row[lo + i], doc[lo + i], s, own[s : s + capacity], total) for s in range(0, full, capacity)]
                    rest += [(row[lo + i], doc[lo + i], s, own[s : s + most], total) for s in range(full, total, most)]
                    if len(rest) >= group or len(whole) >= group:
                        yield from flush()
        yield from flush()

    return run


def pack(docs: DataFrame, tokenizer_path: str, capacity: int = 2048, end_id: int = 1, group: int = GROUP_PIECES, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """Pieces of all documents in sequences of at most `capacity` ids: row_id, doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset (and ids).

    A document longer than a sequence fills whole sequences first. What is left is cut to a quarter of a sequence and spread by
    multiway differencing over the fewest windows that could hold it; their number rises whenever one is over full, so
    windows come out near equal. Pieces of one document that meet in a window in order are one. Null and empty texts
    are one end id. No shuffle: each task packs its own rows in groups of `group` pieces, so memory is bounded by a
    group and one text. Ids repeat when a task is run again, as they come from the partition. Repeated rows are packed
    each, under their own row_id; an empty table gives no pieces; other columns of docs are not read.
    """
    rows = docs.select(F.monotonically_increasing_id().alias("row_id"), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(_pack(tokenizer_path, capacity, end_id, group, with_ids), _SCHEMA + ", ids array<int>" * with_ids)


def op4_packing(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return pack(docs, public_tokenizers.path("word_bpe_49k.json")).drop("row_id")
