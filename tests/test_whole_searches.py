"""Searches that share states give what the whole enumeration gives, and end on inputs that a count of pops would leave open."""

import math
import random
import sys
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))
from test_automata import random_regex, random_tokenizer  # noqa: E402
from test_search import random_model  # noqa: E402

from patternlm.operators import measures as ms  # noqa: E402
from patternlm.operators.model import CountModel, NextTokenModel  # noqa: E402
from patternlm.operators.traverse import best_first, best_listed, lower, run_query  # noqa: E402
from patternlm.plans import workloads as wl  # noqa: E402
from patternlm.plans.query import PatternQuery, Rules, edits  # noqa: E402
from patternlm.queries import experiments as ex  # noqa: E402


def test_a_limit_gives_the_head_of_the_whole_search():
    rng = random.Random(5)
    for n in range(60):
        tok = random_tokenizer(rng)
        pre = (edits(1, "abc"),) if n % 3 == 0 else ()
        q = PatternQuery(random_regex(rng, 2), random_regex(rng, 1) if n % 2 else "", "all", Rules(top_k=rng.choice([None, 2, 3])), preprocessors=pre, max_tokens=4, alphabet="abc", prefix_order=rng.choice(["model", "zero"]))
        dfa, model = lower(q, tok).dfa, random_model(rng, len(tok.vocab))
        whole = [(m.order_cost, m.tokens, m.n_prefix) for m in best_first(dfa, model, q)]
        for k in (1, 2, 7):
            got = [(m.order_cost, m.tokens, m.n_prefix) for m in best_first(dfa, model, q, limit=k)]
            assert [g[1:] for g in got] == [w[1:] for w in whole[:k]] and all(math.isclose(a[0], b[0], abs_tol=1e-9) for a, b in zip(got, whole, strict=False))


def test_canonical_search_equals_scoring_every_string():
    rng = random.Random(6)
    tok = wl.Tokenizer([("a", "b"), ("ab", "c"), ("b", "c"), ("c", " "), (" ", "a")], "abc '")
    model = random_model(rng, len(tok.vocab))
    for body in ("abc abcab", "ab'c bca", "a  bc  a"):
        for prefix in ("", "ca "):
            q = PatternQuery(body, prefix, rules=Rules(top_k=6), preprocessors=(edits(2, "abc "),))
            assert lower(q, tok, lazy=True).check is not None
            want = list(best_listed(q.automaton(), model, q, tok, 5))
            got = run_query(q, model, tok, 5)
            assert [tuple(r[2]) for r in got] == [m.tokens for m in want] and [r[9] for r in got] == [m.n_edits for m in want]


def test_rules_of_single_tokens_equal_those_of_the_distribution():
    rng = random.Random(7)
    for _ in range(20):
        m = random_model(rng, 30)
        for ctx in [(), (-1,), (1, 2), (9, 9)]:
            for k in (None, 3, 8):
                asked = [*range(30), -2]
                assert m.ruled(ctx, asked, Rules(top_k=k)) == NextTokenModel.ruled(m, ctx, asked, Rules(top_k=k))


def test_long_prompt_counts_as_extracted(spark, monkeypatch):
    import public_tokenizers

    tok = wl.PublicTokenizer(public_tokenizers.path("byte_bpe_50k.json"))
    counts: dict = {}
    path = [-1, *tok.encode("you are an idiof"), -2]
    for i in range(1, len(path)):
        for o in range(min(3, i + 1)):
            f = counts.setdefault(tuple(path[i - o : i]), {})
            f[path[i]] = f.get(path[i], 0) + 1
    prompt = "xqzvkj wqpzxk jjvqyw zkxqpv an "
    monkeypatch.setattr(ex, "_toxic_model", lambda *_: (CountModel(counts, 3, len(tok.vocab)), tok))
    monkeypatch.setattr(wl, "toxic_inputs", lambda s, d: s.createDataFrame([(1, prompt + "idiot", "idiot", prompt)], "query_id long, sentence string, hit string, prompt string"))
    found, asked = ex.toxic_run(spark, "", "prompted", "all", 1)
    assert ms.success_rate(found, asked.select("query_id")).first()["successes"] == 1


def test_volume_counts_more_than_twenty_matches(spark, monkeypatch):
    import public_tokenizers

    tok = wl.PublicTokenizer(public_tokenizers.path("byte_bpe_50k.json"))
    word = "a banana"
    parts = {word[i:j] for i in range(len(word)) for j in range(i + 1, len(word) + 1)} & set(tok.vocab)
    counts = {(): {tok.vocab[p]: 1 for p in parts} | {-2: 1}}
    n = tok.count_encodings(word)
    assert len(parts) < 40 and n > 20
    monkeypatch.setattr(ex, "_toxic_model", lambda *_: (CountModel(counts, 3, len(tok.vocab)), tok))
    monkeypatch.setattr(wl, "toxic_inputs", lambda s, d: s.createDataFrame([(1, word, "", "")], "query_id long, sentence string, hit string, prompt string"))
    assert n <= ex.q_tox_volume(spark, "").first()["volume"] <= 1000


def test_bias_model_holds_every_english_sentence_and_draws_5000_a_group(spark, tmp_path):
    spark.createDataFrame([(1, "what is this the end. that was by us. zebra and yak", "en")], "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    model, tok = ex._characters(spark, str(tmp_path), 3)
    assert tok.vocab["z"] in model.counts[()]
    n = {r["x"]: r["n"] for r in ex.q_bias_edits(spark, str(tmp_path)).groupBy("x").agg({"n": "sum"}).withColumnRenamed("sum(n)", "n").collect()}
    assert n == {"this": 5000, "that": 5000}
