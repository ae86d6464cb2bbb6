"""Token counts by greedy longest match in linear time: a vocabulary trie with failure links that know how many tokens they pop."""

from __future__ import annotations

from collections import deque
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geohist.llm.common import as_strings, steps

#: A word is a punctuation mark or a run of anything else without white space.
_WORD = regex.compile(r"[\p{P}$+<=>^`|~]|[^\p{P}$+<=>^`|~\s]+")


#: Characters of a run that is remembered at most: with the number of runs this bounds a worker's memory.
LONG = 64


class CountingMatcher:
    """Number of word pieces of a word, without building them.

    Two tries share one automaton: pieces that begin a word, and pieces that continue one under a second root. At a
    node that cannot go on, the failure link leaves for the place where the rest of what was read stands after
    greedy matching, and `pops` says how many tokens that closes. A word that cannot be cut counts as one unknown token.
    """

    def __init__(self, initial: Iterable[str], continuing: Iterable[str]):
        self.next: list[dict[str, int]] = [{}, {}]
        whole = [False, False]
        depth_parent: list[tuple[int, str]] = [(-1, ""), (-1, "")]

        def insert(root: int, piece: str) -> None:
            v = root
            for c in piece:
                w = self.next[v].get(c)
                if w is None:
                    w = self.next[v][c] = len(self.next)
                    self.next.append({})
                    whole.append(False)
                    depth_parent.append((v, c))
                v = w
            whole[v] = True

        for p in initial:
            if p:
                insert(0, p)
        for p in continuing:
            if p:
                insert(1, p)
        n = len(self.next)
        self.fail, self.pops = [-1] * n, [0] * n
        queue = deque([*self.next[0].values(), *self.next[1].values()])
        while queue:
            v = queue.popleft()
            queue.extend(self.next[v].values())
            if whole[v]:
                self.fail[v], self.pops[v] = 1, 1
                continue
            u, c = depth_parent[v]
            z, popped = self.fail[u], self.pops[u]
            while z >= 0 and c not in self.next[z]:
                z, popped = self.fail[z], popped + self.pops[z]
            if z >= 0:
                self.fail[v], self.pops[v] = self.next[z][c], popped

    def count(self, word: str) -> int:
        """Pieces of one word; 0 if it cannot be cut."""
        v, total, nxt, fail = 0, 0, self.next, self.fail
        for c in word:
            w = nxt[v].get(c)
            while w is None:
                total += self.pops[v]
                v = fail[v]
                if v < 0:
                    return 0
                w = nxt[v].get(c)
            v = w
        while v != 1:
            total += self.pops[v]
            v = fail[v]
            if v < 0:
                return 0
        return total


def pieces_of_model(path: str) -> tuple[list[str], list[str]]:
    """Initial and continuing pieces of a sentencepiece file: those with and without its word mark."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    plain = [sp.id_to_piece(i) for i in range(sp.get_piece_size()) if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i))]
    return [p[1:] for p in plain if p.startswith("▁") and len(p) > 1], [p for p in plain if not p.startswith("▁")]


_MATCHERS: dict[str, tuple[CountingMatcher, dict[str, tuple[int, int, int]]]] = {}


def count_tokens(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", known: int = 400_000) -> DataFrame:
    """(doc_id, n_words, n_tokens, n_unknown) of every whole text; null and empty texts have none.

    Each distinct run without white space is matched once in a worker (up to `known` runs are remembered, none of over
    LONG characters). Repeated rows and ids are counted each on its own; an empty table gives an empty result; other
    columns are not read, whatever their names.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if model_path not in _MATCHERS:
            _MATCHERS[model_path] = (CountingMatcher(*pieces_of_model(model_path)), {})
        matcher, seen = _MATCHERS[model_path]

        def measured(chunk: str) -> tuple[int, int, int]:
            words = tokens = unknown = 0
            for w in _WORD.findall(chunk):
                k = matcher.count(w)
                words += 1
                tokens += k or 1
                unknown += not k
            return words, tokens, unknown

        for b in batches:
            texts = as_strings(b.column(1))
            for lo, hi in steps(texts):
                lists = pc.ascii_split_whitespace(texts.slice(lo, hi - lo))
                ends = np.concatenate([[0], np.cumsum(pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64))])
                coded = lists.flatten().dictionary_encode()
                if len(seen) > known:
                    seen.clear()
                table = []
                for w in coded.dictionary.to_pylist():
                    got = seen.get(w)
                    if got is None:
                        got = measured(w)
                        if len(w) <= LONG:
                            seen[w] = got
                    table.append(got)
                per = np.array(table, np.int64).reshape(-1, 3)[coded.indices.to_numpy(zero_copy_only=False)] if table else np.zeros((0, 3), np.int64)
                total = np.concatenate([np.zeros((1, 3), np.int64), np.cumsum(per, axis=0)])
                out = total[ends[1:]] - total[ends[:-1]]
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), *(pa.array(np.ascontiguousarray(out[:, j])) for j in range(3))], ["doc_id", "n_words", "n_tokens", "n_unknown"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_words long, n_tokens long, n_unknown long")


def op10_token_counts(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return count_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("piece_bpe_32k.model"))
