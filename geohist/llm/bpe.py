"""Byte-level BPE: exact merges by backtracking over longest token matches, decoding by an offset table."""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geohist.llm.common import as_strings, steps

#: Distinct pre-tokens that a worker keeps encoded, and their characters; beyond either the table starts anew.
KNOWN_PIECES, KNOWN_CHARS = 400_000, 16_000_000

#: The pre-token pattern of this family of vocabularies.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def byte_alphabet() -> list[str]:
    """The printable stand-in of each byte in vocabulary files: visible Latin-1 as is, others from 256 up."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out = {b: chr(b) for b in shown}
    for b in range(256):
        out.setdefault(b, chr(256 + len(out) - len(shown)))
    return [out[b] for b in range(256)]


class BpeCodec:
    """Encoder and decoder of one vocabulary file.

    Tokens are numbered by age: single bytes first, then each merge in order, so a lower number merges earlier.
    A token pair is compatible when undoing merges on both sides of their border never meets a merge that BPE
    would have done across it earlier. The encoder walks greedily over the longest token at each position and
    takes a shorter one, or steps back, where a pair is not compatible: what remains are exactly BPE's tokens.
    """

    def __init__(self, path: str):
        import ahocorasick
        import regex
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.split = regex.compile(PATTERN).findall
        self.pre = Tokenizer.from_file(path).pre_tokenizer
        self.checked: set[str] = set(map(chr, range(128)))
        self.disputed: set[str] = set()
        vocab, alphabet = spec["model"]["vocab"], byte_alphabet()
        plain = {c: chr(b) for b, c in enumerate(alphabet)}
        self.ids, self.text, self.halves, self.pair = [], [], [], {}
        age: dict[str, int] = {}

        def born(name: str, halves: tuple[int, int] | None) -> None:
            n = age[name] = len(self.ids)
            self.ids.append(vocab[name])
            self.text.append("".join(plain[c] for c in name))
            self.halves.append(halves or (n, n))

        for c in alphabet:
            born(c, None)
        for m in spec["model"]["merges"]:
            a, b = m if isinstance(m, list) else m.split(" ")
            if a + b not in age:
                born(a + b, (age[a], age[b]))
            self.pair.setdefault((age[a], age[b]), age[a + b])
        self.length = [len(t) for t in self.text]
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.added = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")")
        by_text = {t: i for i, t in enumerate(self.text)}
        self.shorter = [next((by_text[t[:k]] for k in range(len(t) - 1, 0, -1) if t[:k] in by_text), -1) for t in self.text]
        self.automaton = ahocorasick.Automaton()
        for i, t in enumerate(self.text):
            self.automaton.add_word(t, i)
        self.automaton.make_automaton()
        self.compatible: dict[tuple[int, int], bool] = {}
        # Offset table: bytes of token id i are blob[offset[i]:offset[i+1]].
        shown = {self.ids[i]: t.encode("latin-1") for i, t in enumerate(self.text)} | {i: s.encode() for s, i in self.special.items()}
        pieces = [shown.get(i, b"") for i in range(max(shown) + 1)]
        self.offset = np.concatenate([[0], np.cumsum([len(p) for p in pieces])])
        self.blob = np.frombuffer(b"".join(pieces), np.uint8)
        self._forget()

    def _forget(self) -> None:
        codec = self

        class Known(dict):
            def __missing__(self, piece: str) -> int:
                return codec._learn(piece)

        self.known, self.flat, self.sizes, self.digits, self.chars = Known(), [], [], [], 0

    def fits(self, a: int, b: int) -> bool:
        """Whether tokens a, b may stand side by side in an encoding; remembered in the compatibility table."""
        key = (a, b)
        got = self.compatible.get(key)
        if got is None:
            if len(self.compatible) > 300_000:
                self.compatible.clear()
            got = self.compatible[key] = self._compare(a, b)
        return got

    def _compare(self, a: int, b: int) -> bool:
        newest = len(self.ids)  # merges at or after this age come too late to matter
        while True:
            across = self.pair.get((a, b))
            if across is not None and across < newest:
                return False
            # Undo the younger of the two border tokens: the left one keeps its right half and the other way round.
            # A merge of equal age counts as done from the left first.
            if a > b:
                inner, newest = self.halves[a][1], a
                if inner != a:
                    a = inner
                    continue
                inner, newest = self.halves[b][0], b + 1
                if inner == b:
                    return True
                b = inner
            else:
                inner, newest = self.halves[b][0], b + 1
                if inner != b:
                    b = inner
                    continue
                inner, newest = self.halves[a][1], a
                if inner == a:
                    return True
                a = inner

    def encode_piece(self, piece: str) -> list[int]:
        """Ages of the tokens of one pre-token, given as Latin-1 characters for bytes."""
        longest = [0] * len(piece)
        for end, token in self.automaton.iter(piece):
            at = end + 1 - self.length[token]
            if self.length[token] > self.length[longest[at]] or not longest[at]:
                longest[at] = token
        for at, c in enumerate(piece):
            if not longest[at]:
                longest[at] = self._byte[c]
        out: list[int] = []
        alive = bytearray(b"\1" * (len(piece) + 1))
        at, token = 0, longest[0]
        while at < len(piece):
            while token >= 0:
                end = at + self.length[token]
                if alive[end] and (not out or self.fits(out[-1], token)):
                    out.append(token)
                    at = end
                    token = longest[at] if at < len(piece) else -1
                    break
                token = self.shorter[token]
            else:
                alive[at] = 0
                token = out.pop()
                at -= self.length[token]
        return out

    @property
    def _byte(self) -> dict[str, int]:
        if not hasattr(self, "_bytes"):
            self._bytes = {t: i for i, t in enumerate(self.text[:256])}
        return self._bytes

    def _learn(self, piece: str) -> int:
        special = self.special.get(piece[1:]) if piece[:1] == "\0" else None  # see pieces()
        ids = [special] if special is not None else [self.ids[t] for t in self.encode_piece(piece.encode("utf-8", "surrogatepass").decode("latin-1"))]
        i = self.known[piece] = len(self.sizes)
        self.chars += len(piece)
        self.flat.append(np.array(ids, np.uint32))
        self.sizes.append(len(ids))
        self.digits.append("".join(f"{x}," for x in ids).encode())
        return i

    def pieces(self, text: str) -> list[str]:
        """Pre-tokens; an added token is marked by a leading NUL, which no other pre-token of its name has."""
        if not any(s in text for s in self.special):
            return self._plain(text)
        out: list[str] = []
        for i, part in enumerate(self.added.split(text)):  # every second one is an added token
            out += ["\0" + part] if i % 2 else self._plain(part)
        return out

    def _plain(self, text: str) -> list[str]:
        if not text.isascii():
            for c in set(text) - self.checked:
                s = f"a{c}1{c}!"
                if [p[1] for p in self.pre.pre_tokenize_str(s)] != self._spans(s):
                    self.disputed.add(c)
                self.checked.add(c)
            if self.disputed and not self.disputed.isdisjoint(text):  # newer or older Unicode tables: take the library's cut
                return [text[a:b] for _, (a, b) in self.pre.pre_tokenize_str(text)]
        return self.split(text)

    def _spans(self, text: str) -> list[tuple[int, int]]:
        at, out = 0, []
        for p in self.split(text):
            out.append((at, at + len(p)))
            at += len(p)
        return out

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, list[bytes]]:
        """Ids of all texts laid end to end, n+1 offsets, and each text's ids as decimals with a comma after each."""
        if len(self.known) > KNOWN_PIECES or self.chars > KNOWN_CHARS:
            self._forget()
        get = self.known.__getitem__
        index = [np.fromiter(map(get, self.pieces(t)), np.int64) for t in texts]
        flat = np.concatenate(self.flat) if self.flat else np.zeros(0, np.uint32)
        size = np.array(self.sizes, np.int64)
        first = np.cumsum(size) - size
        at = np.concatenate(index) if index else np.zeros(0, np.int64)
        n = size[at]
        ends = np.concatenate([[0], np.cumsum(n)])
        ids = flat[np.repeat(first[at] - ends[:-1], n) + np.arange(ends[-1])]
        digits = self.digits
        shown = [b"".join([digits[i] for i in x.tolist()]) for x in index]
        return ids, ends[np.concatenate([[0], np.cumsum([len(x) for x in index])])], shown

    def decode_bytes(self, ids: np.ndarray, off: np.ndarray) -> list[bytes]:
        """Bytes of each run ids[off[i]:off[i+1]], gathered through the offset table."""
        begin, n = self.offset[ids], self.offset[ids + 1] - self.offset[ids]
        ends = np.concatenate([[0], np.cumsum(n)])
        raw = self.blob[np.repeat(begin - ends[:-1], n) + np.arange(ends[-1])].tobytes()
        cut = ends[off]
        return [raw[a:b] for a, b in zip(cut[:-1].tolist(), cut[1:].tolist())]


_CODECS: dict[str, BpeCodec] = {}


def codec(path: str) -> BpeCodec:
    if path not in _CODECS:
        _CODECS.clear()
        _CODECS[path] = BpeCodec(path)
    return _CODECS[path]


def encode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids array<int>) of every row; null and empty texts have no tokens.

    Repeated rows and ids are encoded each on its own; an empty table gives an empty result; other columns are not read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for b in batches:
            texts = as_strings(b.column(1))
            for lo, hi in steps(texts):
                ids, off, _ = c.encode(texts.slice(lo, hi - lo).to_pylist())
                lists = pa.ListArray.from_arrays(pa.array(off, pa.int32()), pa.array(ids.astype(np.int32)))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), pa.array(np.diff(off)), lists], ["doc_id", "n_tokens", "ids"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, n_tokens long, ids array<int>")


def decode(coded: DataFrame, path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(doc_id, text) of every row of ids; null ids give the empty text, bytes that are no UTF-8 become U+FFFD."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for b in batches:
            lists = [x or [] for x in b.column(1).to_pylist()]
            off = np.concatenate([[0], np.cumsum([len(x) for x in lists])]).astype(np.int64)
            raw = c.decode_bytes(np.array([i for x in lists for i in x], np.int64), off)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([r.decode("utf-8", "replace") for r in raw])], ["doc_id", "text"])

    return coded.select(F.col(id_col).cast("long").alias("doc_id"), F.col(ids_col).alias("ids")).mapInArrow(run, "doc_id long, text string")


def round_trip_digests(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encode and decode every whole text in one pass: (doc_id, n_tokens, ids_sha256, decoded_sha256)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for b in batches:
            texts = as_strings(b.column(1))
            for lo, hi in steps(texts):
                ids, off, shown = c.encode(texts.slice(lo, hi - lo).to_pylist())
                back = c.decode_bytes(ids.astype(np.int64), off)
                sha = [hashlib.sha256(s[:-1]).hexdigest() for s in shown]
                text = [hashlib.sha256(x.decode("utf-8", "replace").encode()).hexdigest() for x in back]
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), pa.array(np.diff(off)), pa.array(sha), pa.array(text)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op7_bpe(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return round_trip_digests(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("byte_bpe_50k.json"))
