"""Jaccard self-join of word n-gram sets and its components: subsets for small sets, inverted lists for large ones."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from geohist.llm.common import Scratch, as_strings, byte_view, gathered_sketch, merged_slices, mix, release_shuffles, row_id, run_hashes, sliced, steps, stored, word_hashes

#: What writes a table between two steps and reads it back.
Keep = Callable[[DataFrame], DataFrame]
#: Words of a shingle; cells of the frequency sketch and slices it is merged in; rows of a list before it is salted.
SHINGLE, CELLS, SLICES, LIST_ROWS = 5, 1 << 20, 64, 20_000
#: Two sets link when LINK[0] * intersection >= LINK[1] * union: 0.8.
LINK = (100, 80)


def shingle_sets(texts: pa.Array, k: int) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text; a text of fewer than k words is one shingle, one without words none."""
    raw, off = byte_view(texts)
    h, _, _, _, word = word_hashes(raw, off, lower=True)
    runs, out = run_hashes(h, k, 3), []
    for a, z in zip(word[:-1].tolist(), word[1:].tolist()):
        if z - a < k:
            out.append(run_hashes(h[a:z], z - a, 100 + z - a) if z > a else runs[:0])
        else:
            x = np.sort(runs[a : z - k + 1])
            out.append(x[np.concatenate([[True], x[1:] != x[:-1]])])
    return out


def _set_key(s: np.ndarray) -> tuple[int, int, int]:
    with np.errstate(over="ignore"):
        return len(s), int(mix(s, 11).sum(dtype=np.uint64)), int(mix(s, 12).sum(dtype=np.uint64))


#: Least bits of a set's parity marks, a power of two; larger sets have as many bits as tokens or up to twice as many.
MARKS = 1024


def parity_marks(s: np.ndarray) -> np.ndarray:
    """Bits flipped once by each token: two sets differ in at least as many tokens as their marks differ in bits."""
    bits = max(MARKS, 1 << (len(s) - 1).bit_length())
    odd = np.bincount((mix(s, 51) & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.int64)


def _halved(marks: Column, other: Column) -> Column:
    """marks at the size of the other set's, which is half theirs at least: the upper half is folded onto the lower."""
    half = F.size(marks) / 2
    fold = F.zip_with(F.slice(marks, F.lit(1), half.cast("int")), F.slice(marks, half.cast("int") + 1, half.cast("int")), lambda x, y: x.bitwiseXOR(y))
    return F.when(F.size(marks) > F.size(other), fold).otherwise(marks)


def _cells(s: np.ndarray) -> np.ndarray:
    return (s >> np.uint64(64 - (CELLS.bit_length() - 1))).astype(np.int64)


class _Seen:
    """Within a task, rows of equal sets share the first one's number as node, so that copies go no further."""

    def __init__(self):
        self.first: dict[tuple[int, int, int], int] = {}

    def node(self, key: tuple[int, int, int], row: int) -> int:
        return self.first.setdefault(key, row) if key[0] else row


def _survey(k: int):
    """Rows (row, doc_id, n, node, key_1 and key_2 of the set), and at the end of a task the slices of its frequency sketch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sketch, seen = np.zeros(CELLS, np.uint32), _Seen()
        names = ["row", "doc_id", "n", "node", "slice", "cells", "key_1", "key_2"]
        for b in batches:
            texts, rows = as_strings(b.column(2)), b.column(0).to_pylist()
            size, node, keys = [], [], ([], [])
            for lo, hi in steps(texts):
                sets = shingle_sets(texts.slice(lo, hi - lo), k)
                for i, s in enumerate(sets):
                    key = _set_key(s)
                    size.append(key[0])
                    for x, v in zip(keys, key[1:]):
                        x.append(v)
                    node.append(seen.node(key, rows[lo + i]))
                sketch += np.bincount(_cells(np.concatenate(sets)), minlength=CELLS).astype(np.uint32)
            n = len(rows)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(size, pa.int64()), pa.array(node, pa.int64()), pa.nulls(n, pa.int32()), pa.nulls(n, pa.binary()), *(pa.array(np.array(x, np.uint64).view(np.int64)) for x in keys)], names)
        for i, cells in sliced(sketch, SLICES):
            yield pa.RecordBatch.from_arrays([*(pa.nulls(1, pa.int64()) for _ in range(4)), pa.array([i], pa.int32()), pa.array([cells], pa.binary()), pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64())], names)

    return run


def prefix_length(n: np.ndarray | int, common: int):
    """Tokens at the front of a set of n, in any order shared by all, among which linked sets share `common`."""
    return n + (-n * LINK[1] // LINK[0]) + common


def boundary_by_cost(sketch: np.ndarray) -> int:
    """Largest size of sets whose two-token subsets cost less than scanning the inverted lists of their prefix.

    A list costs itself and the partners expected on it: the excess of the rarer fifth of all tokens (the prefix
    holds the rarest) over what a cell holds by chance.
    """
    total = int(sketch.sum(dtype=np.uint64))
    if not total:
        return 4
    c = np.sort(sketch).astype(np.float64)
    mass = np.cumsum(c)
    rare = c[: int(np.searchsorted(mass, total / 5)) + 1]
    partners = max(0.0, (rare**2).sum() / max(rare.sum(), 1.0) - total / len(c))
    n = np.arange(2, 2001)
    p2, p1 = prefix_length(n, 2), prefix_length(n, 1)
    cheap = p2 * (p2 - 1) // 2 <= p1 * (1 + partners)
    return int(n[cheap].max(initial=4))


def excess(sketch: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """How often each cell's tokens occur beyond what a cell holds by chance, and the rank of its count among all cells.

    The first is 0 for cells of rare tokens, however large the input. Ranks are quantiles, closer together towards the
    most frequent, so that they tell tokens apart at every size of input.
    """
    usual = float(np.median(sketch))
    steps_ = np.quantile(sketch, [i / 32 for i in range(1, 32)] + [1 - 2.0**-j / 32 for j in range(1, 16)])
    return np.maximum(sketch.astype(np.int64) - int(usual + 6 * usual**0.5), 0), np.searchsorted(np.unique(steps_), sketch).astype(np.uint64)


def _signatures(k: int, boundary: int, sent):
    """(sig, salt, node, meta) rows, meta holding size, position and whether it stands for one token: for each distinct set of a task its whole key, and subsets or list entries of its prefix.

    The position of a token is its place in the set's order, that of a two-token subset the place of its second one
    less one, so that size less position bounds the shared tokens either way; the whole key has -1.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (counts, rank), seen = excess(sent.value), _Seen()
        bridge = -(-boundary * LINK[1] // LINK[0])  # small sets from here may link to large ones
        for b in batches:
            texts, rows = as_strings(b.column(2)), b.column(0).to_pylist()
            for lo, hi in steps(texts):
                out: list[list[np.ndarray]] = [[], [], []]
                dealt: list[np.ndarray] = []

                def put(sig, often, node, n, at, single, out=out, dealt=dealt):
                    m = len(sig)
                    salts = often // LIST_ROWS  # of long lists; others have salt 0
                    salt = np.where(salts > 0, 1 + mix(np.full(m, node, np.uint64), 21) % np.maximum(salts, 1).astype(np.uint64), 0)
                    meta = (np.int64(n) << 33) | ((at.astype(np.int64) + 1) << 1) | int(single)
                    for x, v in zip(out, (sig.view(np.int64), np.full(m, node), meta)):
                        x.append(v)
                    dealt.append(salt.astype(np.int32))

                for i, s in enumerate(shingle_sets(texts.slice(lo, hi - lo), k)):
                    n, key = len(s), _set_key(s)
                    node = rows[lo + i]
                    if not n or seen.node(key, node) != node:
                        continue
                    cells = _cells(s)
                    order = np.argsort((rank[cells] << np.uint64(58)) | (s >> np.uint64(6)), kind="stable")
                    often = counts[cells[order]]
                    t = s[order]
                    put(mix(np.array([key[1]], np.uint64), 31), often[:1], node, n, np.array([-1]), False)
                    if n == 1:
                        continue
                    if n <= boundary:
                        p = prefix_length(n, 2)
                        a, c = np.triu_indices(p, 1)
                        low, high = np.minimum(t[a], t[c]), np.maximum(t[a], t[c])
                        with np.errstate(over="ignore"):
                            put(mix(low * np.uint64(0x9E3779B97F4A7C15) + high, 32), np.minimum(often[a], often[c]), node, n, c - 1, False)
                    if n > boundary or n >= bridge:
                        p = prefix_length(n, 1)
                        put(mix(t[:p], 33), often[:p], node, n, np.arange(p), True)
                if out[0]:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in (out[0], dealt, out[1], out[2])], ["sig", "salt", "node", "meta"])

    return run


def _same_size(a: Column, b: Column) -> Column:
    return LINK[0] * F.least(a, b) >= LINK[1] * F.greatest(a, b)


def _may_link(n_a: Column, n_b: Column, at_a: Column, at_b: Column) -> Column:
    """Whether two sets may link whose first shared token, or subset of the first two, stands at these positions; whole keys have position -1.

    Linked sets pass on the list of the first they share, so this may be asked of every list.
    """
    need = F.ceil((n_a + n_b) * F.lit(LINK[1]) / F.lit(LINK[0] + LINK[1]) - 1e-9)
    return _same_size(n_a, n_b) & ((at_a < 0) | (F.least(n_a - at_a, n_b - at_b) >= need))


def _size_of(meta: str) -> Column:
    return F.shiftright(meta, 33).cast("int")


def _position_of(meta: str) -> Column:
    return (F.shiftright(meta, 1).bitwiseAND(F.lit(0xFFFFFFFF)) - 1).cast("int")


def _node_sets(k: int, sent):
    """(node, n, marks, tokens) of the nodes that a bit table of fixed size does not rule out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted, seen = sent.value, _Seen()
        for b in batches:
            rows = b.column(0).to_numpy()
            hit = np.flatnonzero(_tested(wanted, rows))
            if not len(hit):
                continue
            texts = as_strings(b.column(2).take(pa.array(hit)))
            for lo, hi in steps(texts):
                sets, own = shingle_sets(texts.slice(lo, hi - lo), k), rows[hit[lo:hi]].tolist()
                kept = [i for i, s in enumerate(sets) if len(s) and seen.node(_set_key(s), own[i]) == own[i]]
                if kept:
                    sets = [sets[i] for i in kept]
                    size = np.array([len(s) for s in sets], np.int64)
                    tokens = pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(size)).astype(np.int32)), pa.array(np.concatenate(sets).view(np.int64)))
                    yield pa.RecordBatch.from_arrays([pa.array([own[i] for i in kept], pa.int64()), pa.array(size), pa.array([parity_marks(s) for s in sets], pa.list_(pa.int64())), tokens], ["node", "n", "marks", "tokens"])

    return run


#: Bits of the table that rules nodes out before their sets are built; larger inputs pass more, none is lost.
NODE_BITS = 1 << 26


def _tested(bits: np.ndarray, rows: np.ndarray) -> np.ndarray:
    at = mix(rows.astype(np.uint64), 41) % np.uint64(len(bits) * 8)
    return (bits[(at >> np.uint64(3)).astype(np.int64)] >> (at & np.uint64(7)).astype(np.uint8)) & 1 == 1


def _node_bits(nodes: DataFrame) -> np.ndarray:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        on: list[np.ndarray] = []
        for b in batches:
            on.append(np.unique(mix(b.column(0).to_numpy().astype(np.uint64), 41) % np.uint64(NODE_BITS)))
        at = np.unique(np.concatenate(on)).astype(np.int64) if on else np.zeros(0, np.int64)
        per = NODE_BITS // SLICES
        for s in range(SLICES):
            own = at[np.searchsorted(at, s * per) : np.searchsorted(at, (s + 1) * per)] - s * per
            if len(own):
                cells = np.zeros(per, np.uint8)
                cells[own] = 1
                yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([np.packbits(cells, bitorder="little").tobytes()], pa.binary())], ["slice", "cells"])

    return gathered_sketch(merged_slices(nodes.select("node").mapInArrow(run, "slice int, cells binary"), "uint8", "or"), "uint8", SLICES, NODE_BITS // 8)


def node_sets(nodes: DataFrame, rows: DataFrame, k: int, keep: Keep) -> DataFrame:
    """Kept (node, n, marks, tokens) of at least the given nodes: every later check reads these, no text again."""
    sent = rows.sparkSession.sparkContext.broadcast(_node_bits(nodes))
    return keep(rows.mapInArrow(_node_sets(k, sent), "node long, n long, marks array<long>, tokens array<long>"))


def sets_of(nodes: DataFrame, sets: DataFrame) -> DataFrame:
    """(node, n, tokens) of kept sets, without most of those that are not among the nodes: a bit table spares them the shuffle."""
    sent = sets.sparkSession.sparkContext.broadcast(_node_bits(nodes))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.filter(pa.array(_tested(sent.value, b.column(0).to_numpy())))

    return sets.select("node", "n", "tokens").mapInArrow(run, "node long, n long, tokens array<long>")


def linked(pairs: DataFrame, sets: DataFrame, keep: Keep) -> DataFrame:
    """Those of the kept (a, b) whose sets link.

    Sizes and parity marks, an upper bound of the intersection, rule most others out; what is left is intersected exactly.
    """
    side = lambda df, c, x: df.select(F.col("node").alias(c), F.col("n").alias(f"n_{c}"), F.col(x).alias(f"{x}_{c}"))
    both = pairs.select("a", "b").join(side(sets, "b", "marks"), "b").join(side(sets, "a", "marks"), "a")
    a, b, n_a, n_b = (F.col(x) for x in ("marks_a", "marks_b", "n_a", "n_b"))
    differ = F.aggregate(F.zip_with(_halved(a, b), _halved(b, a), lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda t, x: t + x)
    total = n_a + n_b
    likely = both.where(_same_size(n_a, n_b)).where((LINK[0] + LINK[1]) * (total - differ) >= 2 * LINK[1] * total).select("a", "b")
    likely = keep(likely)
    own = keep(sets_of(likely.select(F.col("a").alias("node")).unionByName(likely.select(F.col("b").alias("node"))), sets))
    both = likely.join(side(own, "b", "tokens"), "b").join(side(own, "a", "tokens"), "a")
    inter = F.size(F.array_intersect("tokens_a", "tokens_b"))
    return keep(both.where(LINK[0] * inter >= LINK[1] * (n_a + n_b - inter)).select("a", "b"))


def components(edges: DataFrame, keep: Keep) -> DataFrame:
    """(node, label): the smallest node of the connected part of each node of the (a, b) rows.

    Every round takes the smallest label around a node and then the label of that label, so paths shrink by half
    or more; each round is written to the shared folder.
    """
    both = keep(edges.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(edges.select(F.col("b").alias("u"), F.col("a").alias("v"))).distinct())
    labels = keep(both.groupBy("u").agg(F.min("v").alias("v")).select(F.col("u").alias("node"), F.least("u", "v").alias("label")))
    while True:
        near = both.join(labels.select(F.col("node").alias("v"), "label"), "v").groupBy("u").agg(F.min("label").alias("near"))
        hop = labels.join(near, labels.node == near.u).select("node", F.col("label").alias("was"), F.least("label", "near").alias("to"))
        jump = labels.select(F.col("node").alias("to"), F.col("label").alias("beyond"))
        moved = keep(hop.join(jump, "to", "left").select("node", "was", F.least("to", F.coalesce("beyond", "to")).alias("label")))
        labels = moved.select("node", "label")
        if moved.where("label != was").isEmpty():
            return labels


#: Sets and tokens of a block of a connected part, all of whose pairs one task counts.
BLOCK_SETS, BLOCK_TOKENS = 256, 1_000_000


def shared_tokens(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """Intersection sizes of all sets of left with all of right."""
    out = np.zeros((len(left), len(right)), np.int64)
    tokens, number = np.unique(np.concatenate([*left, *right]), return_inverse=True)
    many = np.bincount(number, minlength=len(tokens))
    column = np.cumsum(many > 1) - 1
    column[many <= 1] = -1  # a token of one set is shared with none
    place = column[number]
    owner = np.repeat(np.arange(len(left) + len(right)), [len(s) for s in [*left, *right]])
    owner, place = owner[place >= 0], place[place >= 0]
    order = np.argsort(place, kind="stable")
    owner, place = owner[order], place[order]
    wide = max(1, 4_000_000 // (len(left) + len(right)))
    for lo in range(0, int(place[-1]) + 1 if len(place) else 0, wide):
        a, z = np.searchsorted(place, (lo, lo + wide))
        has = np.zeros((len(left) + len(right), min(wide, int(place[-1]) + 1 - lo)), np.float32)
        has[owner[a:z], place[a:z] - lo] = 1
        out += np.rint(has[: len(left)] @ has[len(left) :].T).astype(np.int64)
    return out


def _block_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, links) of each pair of blocks; rows come sorted by part and pair of blocks."""
    key, held = None, []

    def counted() -> pa.RecordBatch:
        lo, hi = key[1:]
        left, right = [r for r in held if r[2] == lo], [r for r in held if r[2] == hi]
        n, m = (np.array([len(r[1]) for r in x], np.int64) for x in (left, right))
        if not len(n) or not len(m):
            return pa.RecordBatch.from_arrays([pa.array([], pa.int64()), pa.array([], pa.int64())], ["node", "links"])
        both = shared_tokens([r[1] for r in left], [r[1] for r in right])
        link = LINK[0] * both >= LINK[1] * (n[:, None] + m[None] - both)
        if lo == hi:
            np.fill_diagonal(link, False)
        found = [(r[0], int(c)) for r, c in zip(left, link @ np.array([r[3] for r in right], np.int64))]
        if lo != hi:
            found += [(r[0], int(c)) for r, c in zip(right, np.array([r[3] for r in left], np.int64) @ link)]
        return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*found)], ["node", "links"])

    for b in batches:
        part, lo, hi, node, own, many = (b.column(c).to_pylist() for c in ("part", "lo", "hi", "node", "own", "many"))
        for i, tokens in enumerate(b.column("tokens")):
            now = (part[i], lo[i], hi[i])
            if now != key:
                if held:
                    yield counted()
                key, held = now, []
            held.append((node[i], tokens.values.to_numpy(), own[i], many[i]))
    if held:
        yield counted()


def link_counts(found: DataFrame, sets: DataFrame, keep: Keep) -> DataFrame:
    """(n, key_1, key_2, n_links): to how many other rows a row of each set links, copies included.

    found has a row for each row of the input: n, key_1, key_2, node, component. Equal sets of all tasks are one, with the
    number of their rows. Sets that link share a connected part; a part is cut into blocks of bounded size and all
    pairs of its blocks are counted, each in one task, by the shared tokens of their sets. No pair becomes a row: a part
    of m sets makes m * m / BLOCK_SETS rows. So the work still grows with the square of a part's different sets.
    """
    c, key = F.col, ["n", "key_1", "key_2"]
    full = found.where("n > 0").groupBy(*key).agg(F.min("component").alias("part"), F.min("node").alias("node"), F.count(F.lit(1)).alias("many"))
    full = keep(full)
    size = full.groupBy("part").agg(F.count(F.lit(1)).alias("sets"), F.sum("n").alias("tokens")).where("sets > 1")
    blocks = F.ceil(F.greatest(c("sets") / BLOCK_SETS, c("tokens") / BLOCK_TOKENS)).cast("int")
    dealt = full.join(size.select("part", blocks.alias("blocks")), "part").withColumn("own", F.pmod(F.xxhash64("node"), c("blocks")).cast("int"))
    dealt = dealt.join(sets_of(keep(dealt.select("node")), sets).drop("n"), "node").withColumn("other", F.explode(F.sequence(F.lit(0), c("blocks") - 1)))
    dealt = dealt.select("part", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"), "node", "own", "many", "tokens")
    counted = dealt.repartition("part", "lo", "hi").sortWithinPartitions("part", "lo", "hi").mapInArrow(_block_counts, "node long, links long")
    counted = counted.groupBy("node").agg(F.sum("links").alias("links"))
    return full.join(counted, "node", "left").select(*key, (c("many") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"))


#: Rounds in which the parts on a list meet its leader before all that is left of it is compared.
ROUNDS = 1


def part_members(entries: DataFrame, labels: DataFrame, keep: Keep) -> DataFrame:
    """Kept entries (sig, salt, node, meta) of the lists that still hold several parts, with their part; those of salted lists all stay.

    Every entry is dealt twice, by its node and by its list: parts of a list are compared where its entries lie, within
    a salt, so that no task gets more of a list than when it was made.
    """
    member = entries.join(labels, "node", "left").withColumn("part", F.coalesce("label", "node")).drop("label")
    of_list = W.partitionBy("sig", "salt")
    member = member.withColumn("low", F.min("part").over(of_list)).withColumn("high", F.max("part").over(of_list))
    return keep(member.where("low < high or salt > 0").drop("low", "high"))


def read_out(member: DataFrame) -> DataFrame:
    """Entries with what their meta holds: size n, position at, and whether they stand for a single token."""
    return member.select("sig", "node", "part", _size_of("meta").alias("n"), _position_of("meta").alias("at"), (F.col("meta") % 2 == 1).alias("single"))


def leader_pairs(member: DataFrame, turn: int, keep: Keep) -> DataFrame:
    """(a, b): for each part the list leader that its own leaders share most lists with.

    A list's leader is the entry at the earliest position: its set has fewest rare tokens of its own, so it stands
    nearest to what the sets of the list have in common. In a later turn another of a part's earliest leads.
    """
    c = F.col
    first = F.struct("at", F.xxhash64("node", F.lit(turn)).alias("dealt"), "node", "n")
    reps = keep(member.groupBy("sig", "part").agg(F.min(first).alias("x")).select("sig", "part", "x.*"))  # read twice
    lead = reps.groupBy("sig").agg(F.min(F.struct("at", "dealt", "node", "n", "part")).alias("y"))
    met = reps.join(lead, "sig").where(c("part") != c("y.part")).where(_may_link(c("y.n"), c("n"), c("y.at"), c("at")))
    best = met.groupBy(c("y.node").alias("to"), "part", "node").agg(F.count(F.lit(1)).alias("shared"))
    best = best.groupBy("part").agg(F.max(F.struct("shared", (-c("to")).alias("back"), "node")).alias("z"))
    return best.select((-c("z.back")).alias("a"), c("z.node").alias("b"))


def pairs_left(member: DataFrame, boundary: int, keep: Keep) -> DataFrame:
    """(a, b), distinct: members of different parts of a list that size and position allow a link."""
    c = F.col
    # What a part can offer on a list: its sizes, and the most tokens from its entry on.
    reach = F.when(c("at") < 0, c("n") + 1).otherwise(c("n") - c("at"))
    parts = keep(member.groupBy("sig", "part").agg(F.min("n").alias("low"), F.max("n").alias("high"), F.max(reach).alias("reach"), F.max("single").alias("one")))
    half = lambda s: parts.select("sig", *(c(x).alias(f"{x}_{s}") for x in ("part", "low", "high", "reach", "one")))
    sizes = (LINK[0] * c("high_a") >= LINK[1] * c("low_b")) & (LINK[0] * c("high_b") >= LINK[1] * c("low_a"))
    enough = F.least("reach_a", "reach_b") >= F.ceil((c("low_a") + c("low_b")) * F.lit(LINK[1]) / F.lit(LINK[0] + LINK[1]) - 1e-9)
    large = ~c("one_a") | (c("high_a") > boundary) | (c("high_b") > boundary)
    across = half("a").join(half("b"), ["sig"]).where((c("part_a") < c("part_b")) & sizes & enough & large).select("sig", "part_a", "part_b")
    side = lambda s: member.select("sig", c("part").alias(f"part_{s}"), c("node").alias(s), c("n").alias(f"n_{s}"), c("at").alias(f"at_{s}"), "single")
    pairs = across.join(side("a"), ["sig", "part_a"]).join(side("b").drop("single"), ["sig", "part_b"])
    pairs = pairs.where(_may_link(c("n_a"), c("n_b"), c("at_a"), c("at_b")) & (~c("single") | (c("n_a") > boundary) | (c("n_b") > boundary)))
    return pairs.select("a", "b").distinct()


def merged_labels(labels: DataFrame, links: DataFrame, keep: Keep) -> DataFrame:
    """(node, label) after links between parts: the smallest node of each joined part."""
    named = labels.withColumnRenamed("label", "part")
    end = lambda df, c: df.join(named.select(F.col("node").alias(c), F.col("part").alias(f"part_{c}")), c, "left")
    joined = end(end(links.select("a", "b"), "a"), "b").select(F.coalesce("part_a", "a").alias("a"), F.coalesce("part_b", "b").alias("b"))
    merged = components(joined.distinct(), keep).select(F.col("node").alias("part"), F.col("label").alias("whole"))
    ends = links.select(F.col("a").alias("node")).unionByName(links.select(F.col("b").alias("node"))).distinct()
    every = ends.join(named, "node", "full").select("node", F.coalesce("part", "node").alias("part"))
    return keep(every.join(merged, "part", "left").select("node", F.coalesce("whole", "part").alias("label")))


def link_components(docs: DataFrame, k: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text", row_col: str | None = None, counts: bool = True) -> DataFrame:
    """One row for each row of docs: row, doc_id, n_shingles, component_id, component (its smallest row), n_links.

    Sets are the distinct k-word shingles of the lower-cased whole text (the whole sequence if shorter); they link from a
    Jaccard similarity of 0.8. Linked rows, directly or over others, share component_id, the smallest doc_id
    among them; rows without words are alone. Null text counts as empty; a null id is never smallest; repeated rows
    are linked rows like others. n_links is the exact number of other rows that the row links to; it is left out
    without counts. Other columns of docs are not read, whatever their names; an empty table gives an empty result.

    docs must give the same rows in the same partitions each time it is read (a file scan does; store others first).
    """
    spark = docs.sparkSession
    scratch = Scratch(spark)
    keep = scratch.keep
    rows = docs.select((F.col(row_col) if row_col else row_id()).alias("row"), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    survey = keep(rows.mapInArrow(_survey(k), "row long, doc_id long, n long, node long, slice int, cells binary, key_1 long, key_2 long"))
    known = survey.where("row is not null").select("row", "doc_id", "n", "node", "key_1", "key_2")
    sketch = gathered_sketch(merged_slices(survey.where("slice is not null"), "uint32", "sum"), "uint32", SLICES, CELLS)
    boundary = boundary_by_cost(sketch)
    listed = rows.mapInArrow(_signatures(k, boundary, spark.sparkContext.broadcast(sketch)), "sig long, salt int, node long, meta long")
    n = _size_of("meta")
    # Lists of one entry end here; the earliest of each size class leads its list. Long lists are dealt by salt.
    listed = listed.withColumn("class", F.floor(F.log(LINK[0] / LINK[1], n) + 1e-9).cast("int"))
    earliest = F.struct(_position_of("meta").alias("at"), "node", "meta")
    listed = listed.withColumn("rows", F.count(F.lit(1)).over(W.partitionBy("sig", "salt"))).withColumn("lead", F.min(earliest).over(W.partitionBy("sig", "salt", "class")))
    listed = listed.where("rows > 1 or salt > 0").select("sig", "salt", "class", "node", "meta", F.col("lead.node").alias("leader"), F.col("lead.meta").alias("leader_meta"))
    listed = keep(listed)
    sets = node_sets(listed.select("node"), rows, k, keep)
    release_shuffles(spark)  # the largest shuffle is over: its files may go
    # First round: each node with the leader it shares most entries with; leaders of one list's salts with the first of them.
    heads = listed.where("salt > 0").groupBy("sig", "class").agg(F.min("leader").alias("first"), F.count_distinct("salt").alias("salts")).where("salts > 1")
    upper = listed.where("leader = node").join(heads, ["sig", "class"]).where("first != node").select(F.col("first").alias("a"), F.col("node").alias("b"))
    lower = listed.where("leader != node").where(_may_link(_size_of("leader_meta"), n, _position_of("leader_meta"), _position_of("meta"))).select(F.col("leader").alias("a"), F.col("node").alias("b"))
    shared = lower.unionByName(upper).groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared"))
    best = shared.groupBy("b").agg(F.max(F.struct("shared", (-F.col("a")).alias("back"))).alias("x")).select((-F.col("x.back")).alias("a"), "b")
    labels = components(linked(keep(best), sets, keep), keep)
    # Then parts with the leaders of lists that hold several, while that joins any; at last, exactly, all members of different parts.
    member = part_members(listed.select("sig", "salt", "node", "meta"), labels, keep)
    for turn in range(ROUNDS):
        links = linked(keep(leader_pairs(read_out(member), turn, keep)), sets, keep)
        if links.isEmpty():
            break
        labels = merged_labels(labels, links, keep)
        member = part_members(member.drop("part"), labels, keep)
    release_shuffles(spark)
    links = linked(keep(pairs_left(read_out(member), boundary, keep)), sets, keep)
    labels = merged_labels(labels, links, keep)
    out = known.join(labels, "node", "left").withColumn("component", F.coalesce("label", "node")).drop("label")
    smallest = out.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    shown = ["row", "doc_id", F.col("n").alias("n_shingles"), "component_id", "component"]
    if counts:
        out = keep(out)
        many = link_counts(out, sets, keep)
        out = out.join(smallest, "component").join(many, ["n", "key_1", "key_2"], "left").select(*shown, F.coalesce("n_links", F.lit(0)).alias("n_links"))
    else:
        out = out.join(smallest, "component").select(*shown)
    out = stored(out, spark)
    scratch.drop()
    return out


def op1_jaccard_join(spark, sf_dir: str) -> DataFrame:
    return link_components(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop("row", "component")
