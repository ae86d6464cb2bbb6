import random
import zlib

import corpus_pipeline
import numpy as np
import public_tokenizers
from geohist.llm import quality
from test_jaccard import brute as linked
from test_substring_quality import SPACE
from tokenizers import Tokenizer


def test_pipeline_equals_brute_force(spark, tmp_path):
    rng = random.Random(12)
    words = ["".join(rng.choice("etaoinshrd") for _ in range(rng.randint(2, 8))) for _ in range(500)]
    passage = " ".join(rng.choice(words) for _ in range(60))
    rows, labels = [], []
    for i in range(240):
        kind = i % 8
        w = [rng.choice(words) for _ in range(rng.randint(30, 120))]
        if kind == 0:
            text = " ".join(x + "%%%" for x in w)
        elif kind == 1 and i > 8:
            text = rows[-2][1] + " "
        elif kind == 2 and i > 8:
            v = SPACE.findall(rows[-1][1])
            v[len(v) // 2] = "changed"
            text = " ".join(v)
        elif kind == 3:
            text = " ".join(w[:20]) + " " + passage + "\n" + " ".join(w[20:])
        else:
            text = " ".join(w)
        rows.append((i, text, "en", f"src{i % 3}", len(text)))
        labels.append((i, int(kind != 0 and "%%%" not in text), 0))
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    docs.repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    stage, out = spark.read.parquet(f"{tmp_path}/documents.parquet"), []
    for i, (_, f) in enumerate(corpus_pipeline.STAGES):
        got = f(spark, stage, str(tmp_path))
        if i < 4:
            assert got.columns == docs.columns
        got.write.parquet(f"{tmp_path}/{i}")
        stage = spark.read.parquet(f"{tmp_path}/{i}")
        out.append(stage.collect())
    kept = [r for r in rows if r[0] in {x["doc_id"] for x in out[0]}]
    good = {d for d, q, _ in labels if q}
    assert len({r[0] for r in kept} ^ good) <= 2
    best: dict = {}
    for r in kept:
        k = "".join(SPACE.findall(r[1]))
        best[k] = min(best.get(k, (1, 0)), (-len(r[1]), r[0]))
    ids = {d for _, d in best.values()}
    assert {x["doc_id"] for x in out[1]} == ids
    kept = [r for r in kept if r[0] in ids]
    ids = {d for d, _, c in linked([r[:2] for r in kept], 5) if d == c}
    assert {x["doc_id"] for x in out[2]} == ids
    kept = [r for r in kept if r[0] in ids]
    first: dict = {}
    for r in kept:
        w = SPACE.findall(r[1])
        for i in range(len(w) - 12):
            first.setdefault(tuple(w[i : i + 13]), r[0])
    want = {}
    for r in kept:
        w = SPACE.findall(r[1])
        gone = {j for i in range(len(w) - 12) if first[tuple(w[i : i + 13])] < r[0] for j in range(i, i + 13)}
        want[r[0]] = " ".join(x for j, x in enumerate(w) if j not in gone) if gone else r[1]
    assert {x["doc_id"]: x["text"] for x in out[3]} == want and all(x["n_chars"] == len(x["text"]) for x in out[3])
    assert sum(passage in t for t in want.values()) == 1
    t, whole = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json")), {}
    for x in sorted(out[4], key=lambda x: (x["doc_id"], x["start"])):
        ids_ = [*t.encode(want[x["doc_id"]], add_special_tokens=False).ids, 1]
        part = ids_[x["start"] : x["start"] + x["length"]]
        assert x["ids_crc32"] == zlib.crc32(np.array(part, "<u4").tobytes()) and whole.get(x["doc_id"], 0) == x["start"]
        whole[x["doc_id"]] = x["start"] + x["length"]
    assert whole.keys() == want.keys()
    assert quality is corpus_pipeline.quality
