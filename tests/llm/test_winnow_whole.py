import random

from geohist.llm import winnow


def test_shared_run_of_eleven_tokens_is_found_and_hashes_are_whole(spark):
    rng, rows = random.Random(3), []
    for i in range(60):
        passage = [f"p{i}x{j}" for j in range(11)]
        for side in "ab":
            fill = lambda m: [f"{side}{i}y{rng.randrange(10**9)}" for _ in range(m)]  # noqa: E731, B023
            rows.append((2 * i + (side == "b"), " ".join(fill(rng.randint(9, 30)) + passage + fill(rng.randint(9, 30)))))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r for r in winnow.with_fingerprint(docs, "text", "g").select("doc_id", winnow.hashes(winnow.F.col("g")).alias("h"), winnow.positions(winnow.F.col("g")).alias("p"), winnow.whole(winnow.F.col("g")).alias("w")).collect()}
    assert all(set(got[2 * i]["h"]) & set(got[2 * i + 1]["h"]) for i in range(60))
    for r in got.values():
        assert [int(r["w"][i : i + 11], 16) for i in range(0, len(r["w"]), 11)] == [p["hash"] for p in r["p"]]
