"""Op 4: letters and marks are learnt apart, with the ids of whole texts."""

import pyarrow as pa
import pytest

P = pytest.importorskip("public_tokenizers")
pytest.importorskip("tokenizers")

from geohist.llm import packing  # noqa: E402


def test_parts_have_the_ids_of_whole_texts():
    from tokenizers import Tokenizer

    path = P.path("word_bpe_49k.json")
    whole = Tokenizer.from_file(path)
    texts = [
        "Word. word, WORD; word", "don't 'S it's. 's.' x'.", "Ünïcödé!! ÉCOLE... Œuvre% é. É! İstanbul. ΣΑΣ. straße,",
        "a1. 12, ... <|endoftext|>. abc<|endoftext|> abc<| <a̸ a≮ ª. ×. x y. ŉ. K. ﬁ, ", "", "¿qué? «oui» “no” don’t. a_b a-b. A@",
    ]
    encoder = packing.ChunkEncoder(path)
    for _ in range(2):
        ids, at = encoder.encode(pa.array(texts, pa.large_string()))
        for i, t in enumerate(texts):
            assert ids[at[i] : at[i + 1]].tolist() == whole.encode(t, add_special_tokens=False).ids, t
    assert encoder.encode(pa.array([], pa.large_string()))[1].tolist() == [0]


def test_words_are_learnt_once_whatever_marks_follow():
    encoder = packing.ChunkEncoder(P.path("word_bpe_49k.json"))
    encoder.encode(pa.array(["Word. word, WORD; word WORD... word%%%"], pa.large_string()))
    assert set(encoder.known) == {"word", "", ".", ",", ";", "...", "%%%"}


def test_other_tokenizers_keep_whole_chunks():
    assert not packing.cuts_at_marks(P.path("byte_bpe_50k.json"))
