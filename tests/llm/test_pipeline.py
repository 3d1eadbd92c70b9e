"""The pipeline's stages against brute force on a small table, and its contract."""

import math
import random
from collections import Counter

import corpus_pipeline
from patternlm.llm import quality_rules


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 5
    seen = {}
    for name, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.cut(stage(spark, docs, sf), name)
        seen[name] = docs
        if name != names[-1]:
            assert docs.columns == columns
    good = quality_rules.quality_rules(spark.read.parquet(f"{sf}/documents.parquet")).where("kept")
    assert {r["doc_id"] for r in good.select("doc_id").collect()} == {r["doc_id"] for r in seen["quality_rules"].select("doc_id").collect()}
    low = lambda t: t.translate({c: c + 32 for c in range(65, 91)})
    best = {}
    for r in seen["quality_rules"].collect():
        best[low(r["text"])] = max(best.get(low(r["text"]), -1), r["doc_id"])
    assert {r["doc_id"] for r in seen["exact_dedup"].collect()} == set(best.values())
    sets = {}
    for r in seen["exact_dedup"].collect():
        w = low(r["text"]).split()
        sets[r["doc_id"]] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)}
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if b < a and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                parent[y] = x
    assert {r["doc_id"] for r in seen["ngram_jaccard_join"].collect()} == {find(i) for i in ids}
    words = lambda df: sum(len(r["text"].split()) for r in df.collect())
    assert abs(words(seen["mix_sources"]) - words(seen["ngram_jaccard_join"])) <= 20
    pieces = seen["best_fit_packing"].collect()
    fill = Counter()
    for r in pieces:
        fill[r["sequence_id"]] += r["length"]
    assert max(fill.values()) <= 1024 and len(fill) <= math.ceil(sum(fill.values()) / 1024) * 1.03 + 1


def test_run_on_empty_and_odd_rows(spark, tmp_path):
    rng = random.Random(1)
    rows = [(1, None, None, None, None, "x"), (2, "", "en", "s", 0, "y"), *[(10 + i, " ".join(rng.choices("the of and a to in cat dog runs far".split(), k=60)), "en", rng.choice(["a", "b", None]), 5, "z") for i in range(8)]]
    schema = "doc_id long, text string, lang string, source string, n_chars long, block string"
    spark.createDataFrame(rows, schema).write.parquet(str(tmp_path / "a/documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path / "a")).count() > 0
    spark.createDataFrame([], schema).write.parquet(str(tmp_path / "b/documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path / "b")).count() == 0
