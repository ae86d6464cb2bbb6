"""Exact duplicates by owner tries: partitions by length and content hash, full byte strings in radix tries."""

from __future__ import annotations

import hashlib
import json
import tempfile
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geohist.llm.common import SPACES, Scratch, free_name, row_id, stored

#: Bytes of keys that a trie holds before it spills its largest subtree.
TRIE_BYTES = 128_000_000


def _shared_prefix(a: bytes, at: int, label: bytes) -> int:
    """Length of the common prefix of a[at:] and label."""
    if a.startswith(label, at):
        return len(label)
    lo, hi = 0, min(len(label), len(a) - at)
    while lo < hi:
        mid = (lo + hi + 1) // 2
        if a[at : at + mid] == label[:mid]:
            lo = mid
        else:
            hi = mid - 1
    return lo


class _Node:
    __slots__ = ("label", "kids", "owner", "gone")

    def __init__(self, label: bytes, owner=None):
        self.label, self.kids, self.owner, self.gone = label, {}, owner, None


class OwnerTrie:
    """Compressed radix trie from byte strings to owners; beyond a bound the largest subtrees go to files without a name.

    An owner is [rank, slots, count]: rank is the smallest tuple seen, so ties go to the smallest identifier. Subtrees
    leave below the first node that branches, however long the prefix that all strings share, and each is
    later read into a trie of its own; the system removes the files when they are read or the task dies.
    """

    def __init__(self, limit: int = TRIE_BYTES):
        self.root, self.limit, self.held, self.spilled = _Node(b""), limit, 0, []

    def add(self, key: bytes, rank: tuple, slots: list[int], count: int) -> None:
        node, at = self.root, 0
        while at < len(key):
            kid = node.kids.get(key[at])
            if kid is None:
                if node.gone and key[at] in node.gone:
                    self._to_disk(node.gone[key[at]], key[at + 1 :], rank, slots, count)
                    return
                node.kids[key[at]] = _Node(key[at:], [rank, list(slots), count])
                self.held += len(key) - at + 200
                if self.held > self.limit:
                    self._spill()
                return
            n = _shared_prefix(key, at, kid.label)
            if n < len(kid.label):
                upper = _Node(kid.label[:n])
                upper.kids[kid.label[n]] = kid
                node.kids[kid.label[0]] = upper
                kid.label = kid.label[n:]
                kid = upper
                self.held += 200
            node, at = kid, at + n
        if node.owner is None:
            node.owner = [rank, list(slots), count]
        else:
            self._merge(node.owner, rank, slots, count)

    @staticmethod
    def _merge(owner: list, rank: tuple, slots: list[int], count: int) -> None:
        owner[0] = min(owner[0], rank)
        owner[1].extend(slots)
        owner[2] += count

    def _walk(self, node: _Node, path: bytes) -> Iterator[tuple[bytes, list]]:
        stack = [(node, path)]
        while stack:
            x, p = stack.pop()
            if x.owner is not None:
                yield p, x.owner
            stack.extend((k, p + k.label) for k in x.kids.values())

    def _size(self, node: _Node) -> int:
        total, stack = 0, [node]
        while stack:
            x = stack.pop()
            total += len(x.label) + 200
            stack.extend(x.kids.values())
        return total

    def _spill(self) -> None:
        """Write the largest subtrees below the first branching node to files, until half the bound is free; a single string stays."""
        top = self.root
        while top.owner is None and not top.gone and len(top.kids) == 1:
            (top,) = top.kids.values()
        sizes = sorted(((self._size(k), b) for b, k in top.kids.items()), reverse=True)
        if top.owner is None and not top.gone and len(sizes) < 2:
            return
        for size, b in sizes:
            if self.held <= self.limit // 2:
                break
            kid = top.kids.pop(b)
            self.held -= size
            file = tempfile.TemporaryFile()  # noqa: SIM115  unlinked from the start, read back by owners()
            top.gone = {**(top.gone or {}), b: file}
            self.spilled.append(file)
            for key, owner in self._walk(kid, kid.label[1:]):
                self._to_disk(file, key, *owner)

    @staticmethod
    def _to_disk(file, key: bytes, rank: tuple, slots: list[int], count: int) -> None:
        head = json.dumps([len(key), rank, slots, count]).encode()
        file.write(len(head).to_bytes(4, "big") + head + key)

    def owners(self) -> Iterator[list]:
        """All owners; spilled subtrees are read back one at a time, below the bytes they share."""
        todo = [self]
        while todo:
            trie = todo.pop()
            if not isinstance(trie, OwnerTrie):
                file, trie = trie, OwnerTrie(self.limit)
                file.seek(0)
                while head := file.read(4):
                    length, rank, slots, count = json.loads(file.read(int.from_bytes(head, "big")))
                    trie.add(file.read(length), tuple(rank), slots, count)
                file.close()
            for _, owner in trie._walk(trie.root, b""):
                yield owner
            trie.root = _Node(b"")
            todo.extend(trie.spilled)


_LOCAL = "row long, doc_id long, slot long, n_chars long, sha string, key_len long, key_hash long, content binary, rank_chars long, rank_id long, rank_row long, rows long"
_BIG = 2**63 - 1


def _local_owners(limit: int):
    """Each task folds its own copies first, so that a text reaches the shuffle once for each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, made = TaskContext.get().partitionId(), 0
        names = [x.split()[0] for x in _LOCAL.split(", ")]
        types = [{"long": pa.int64(), "string": pa.string(), "binary": pa.binary()}[x.split()[1]] for x in _LOCAL.split(", ")]

        def rows(cols: dict) -> pa.RecordBatch:
            n = len(next(iter(cols.values())))
            return pa.RecordBatch.from_arrays([pa.array(cols[c], t) if c in cols else pa.nulls(n, t) for c, t in zip(names, types)], names)

        trie, keys = OwnerTrie(_BIG), {}

        def flush() -> Iterator[pa.RecordBatch]:
            nonlocal trie, keys, made
            members: dict[str, list] = {c: [] for c in ("row", "doc_id", "slot", "n_chars", "sha")}
            heads: dict[str, list] = {c: [] for c in ("slot", "key_len", "key_hash", "content", "rank_chars", "rank_id", "rank_row", "rows")}
            size = 0
            for key, owner in trie._walk(trie.root, b""):
                slot = (part << 40) | made
                made += 1
                (chars, doc, row), sha = owner[0], hashlib.sha256(key).hexdigest()
                for i in owner[1]:
                    r, d, c = keys[i]
                    for name, v in zip(members, (r, d, slot, c, sha)):
                        members[name].append(v)
                for name, v in zip(heads, (slot, len(key), xxhash.xxh64_intdigest(key) - 2**63, key, -chars, None if doc == _BIG else doc, row, owner[2])):
                    heads[name].append(v)
                size += len(key)
                if size > 8_000_000:
                    yield rows(heads)
                    heads, size = {c: [] for c in heads}, 0
            if heads["slot"]:
                yield rows(heads)
            if members["row"]:
                yield rows(members)
            trie, keys = OwnerTrie(_BIG), {}

        for b in batches:
            for row, doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                t = text.as_py() or ""
                key = t.encode("utf-8", "surrogatepass").translate(None, SPACES)
                i = len(keys)
                keys[i] = (row, doc, len(t))
                trie.add(key, (-len(t), _BIG if doc is None else doc, row), [i], 1)
            if trie.held > limit or len(keys) > 500_000:
                yield from flush()
        yield from flush()

    return run


def _global_owners(limit: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie = OwnerTrie(limit)
        for b in batches:
            slot, chars, doc, row, n = (b.column(c).to_pylist() for c in ("slot", "rank_chars", "rank_id", "rank_row", "rows"))
            for i, key in enumerate(b.column("content")):
                trie.add(key.as_py(), (-chars[i], _BIG if doc[i] is None else doc[i], row[i]), [slot[i]], n[i])
        out: list[list] = [[], [], [], []]
        for (_, doc, row), slots, n in trie.owners():
            for s in slots:
                for x, v in zip(out, (s, None if doc == _BIG else doc, row, n)):
                    x.append(v)
            if len(out[0]) > 50_000:
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in out], ["slot", "keep_id", "keep_row", "group_size"])
                out = [[], [], [], []]
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in out], ["slot", "keep_id", "keep_row", "group_size"])

    return run


def exact_owners(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", row_col: str | None = None, limit: int = TRIE_BYTES) -> DataFrame:
    """One row for each row of docs: row_id, doc_id, keep_id, keep_row, group_size, kept, text_sha256.

    Texts are equal when their bytes are, white space of `SPACES` deleted; null counts as empty. The row with
    most code points stays, then the smallest id (null last), then the first row, so of repeated rows one stays.
    Each task first folds its copies in a trie of its own; one string for each task and text is then
    partitioned by length and content hash and inserted whole into the owner trie of its partition. An empty table
    gives an empty result; other columns of docs are not read, whatever their names.
    """
    spark = docs.sparkSession
    rows = docs.select((F.col(row_col) if row_col else row_id()).alias("row"), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    scratch = Scratch(spark)
    local = scratch.keep(rows.mapInArrow(_local_owners(limit // 2), _LOCAL))
    heads = local.where("content is not null").select("slot", "key_len", "key_hash", "content", "rank_chars", "rank_id", "rank_row", "rows")
    owners = heads.repartition("key_len", "key_hash").mapInArrow(_global_owners(limit), "slot long, keep_id long, keep_row long, group_size long")
    members = local.where("sha is not null").select("row", "doc_id", "slot", "sha")
    found = members.join(owners, "slot").select(
        F.col("row").alias("row_id"), "doc_id", "keep_id", "keep_row", "group_size", (F.col("row") == F.col("keep_row")).alias("kept"), F.col("sha").alias("text_sha256")
    )
    found = stored(found, spark)  # a few numbers a row; the texts written before go
    scratch.drop()
    return found


def drop_exact(docs: DataFrame, **options) -> DataFrame:
    """docs without the rows that exact_owners drops; all columns stay as they are."""
    mark = free_name(docs, "row_mark")
    marked = docs.withColumn(mark, row_id())
    keep = exact_owners(docs, **options).where("kept").select(F.col("row_id").alias(mark))
    return marked.join(keep, mark, "left_semi").drop(mark)


def op2_exact_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return exact_owners(docs).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


OP2_SQL = """
WITH t AS (
  SELECT doc_id, coalesce(text, '') AS text, regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]', '', 'g') AS norm FROM documents
), k AS (
  SELECT doc_id, sha256(norm) AS text_sha256,
    first_value(doc_id) OVER (PARTITION BY norm ORDER BY length(text) DESC, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS keep_id,
    count(*) OVER (PARTITION BY norm) AS group_size
  FROM t
)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256 FROM k
"""
