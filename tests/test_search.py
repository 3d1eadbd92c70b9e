"""Models, best-first search, sampling and measures: worked examples, invariants against enumeration, exact sampling."""

import math
import random
import sys
from collections import Counter
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent))
from test_automata import random_regex, random_tokenizer  # noqa: E402

from patternlm.functions import automata as fa  # noqa: E402
from patternlm.functions.tokenizer import BOS, EOS, Tokenizer  # noqa: E402
from patternlm.operators import graph, measures, walks  # noqa: E402
from patternlm.operators.model import CallableModel, CountModel, ModelTooLarge, TableModel, UniformModel, arcs, fit_ngram, score_batches  # noqa: E402
from patternlm.operators.traverse import MATCHES, Sampler, best_first, frontier_search, iterate, lower, run_query, sample  # noqa: E402
from patternlm.plans import planner  # noqa: E402
from patternlm.plans.query import PatternQuery, Rules, edits, erase, exclude, synonyms  # noqa: E402

SIX = Tokenizer([], vocab={t: i for i, t in enumerate(("T", "h", "e", "Th", "he", "The"))})
T_, H_, E_, TH, HE, THE = range(6)
TABLE = TableModel({(): {THE: 0.6, TH: 0.3, T_: 0.1}, (TH,): {E_: 0.9, H_: 0.06, T_: 0.04}, (T_,): {H_: 0.5, HE: 0.5}, (T_, H_): {E_: 1.0}}, 6)


def test_encodings_of_a_word_under_rules():
    q = PatternQuery("The", encoding="all")
    assert [r[2] for r in run_query(q, TABLE, SIX)] == [[THE], [TH, E_], [T_, H_, E_], [T_, HE]]
    assert [r[2] for r in run_query(q.but(rules=Rules(top_k=2)), TABLE, SIX)] == [[THE], [TH, E_]]
    assert [r[2] for r in run_query(q.but(rules=Rules(top_p=0.65)), TABLE, SIX)] == [[THE], [TH, E_]]
    assert len(run_query(q, TABLE, SIX, distinct_on="text")) == 1


def random_model(rng, vocab, order=3):
    counts = {}
    for _ in range(120):
        path = [BOS] + [rng.randrange(vocab) for _ in range(rng.randint(1, 5))] + [EOS]
        for i in range(1, len(path)):
            for o in range(min(order, i + 1)):
                f = counts.setdefault(tuple(path[i - o : i]), {})
                f[path[i]] = f.get(path[i], 0) + 1
    return CountModel(counts, order, vocab)


def test_count_model_is_proper_and_ranks_unseen_tokens():
    rng = random.Random(1)
    m = random_model(rng, 6)
    for ctx in [(), (BOS,), (1, 2), (5, 5), (9, 9)]:
        assert math.isclose(sum(math.exp(m.logp(ctx, t)) for t in [*range(6), EOS]), 1, rel_tol=1e-9)
    wide = CountModel(m.counts, 3, 50)
    lps = {t: wide.logp((1,), t) for t in [*range(50), EOS]}
    best = sorted(lps, key=lambda t: (-lps[t], t))[:12]
    got = [t for t, lp in zip(lps, wide.ruled((1,), list(lps), Rules(top_k=12)), strict=True) if lp > -math.inf]
    assert sorted(got) == sorted(best)


def brute(dfa, model, query):
    """Every path up to the token limit whose body tokens the rules allow, sorted by cost and tokens."""
    out = []
    for path in fa.enumerate_language(dfa, query.max_tokens):
        cost = score = state = 0
        ok = True
        for i, t in enumerate(path):
            ctx, body = (BOS, *path[:i]), (state, t) not in dfa.prefix
            lp = model.ruled(ctx, [t], query.rules if body else Rules())[0]
            ok = ok and lp > -math.inf
            cost -= lp if body or query.prefix_order == "model" else 0
            score -= lp if body else 0
            state = dfa.edges[state][t]
        if ok:
            out.append((cost, path, score))
    return sorted(out)


def test_best_first_equals_sorted_enumeration():
    rng = random.Random(2)
    for n in range(80):
        tok = random_tokenizer(rng)
        q = PatternQuery(random_regex(rng, 3), random_regex(rng, 1) if n % 2 else "", "all", Rules(top_k=rng.choice([None, 2, 3])), max_tokens=4, alphabet="abc", prefix_order=rng.choice(["model", "zero"]))
        dfa = lower(q, tok).dfa
        model = random_model(rng, len(tok.vocab))
        got = [(m.order_cost, m.tokens, -m.logp) for m in best_first(dfa, model, q)]
        want = brute(dfa, model, q)
        assert sorted(t for _, t, _ in got) == sorted(t for _, t, _ in want)
        assert len({t for _, t, _ in got}) == len(got)
        for a, b in zip(got, want, strict=True):
            assert math.isclose(a[0], b[0], abs_tol=1e-9) and math.isclose(a[2], {t: s for _, t, s in want}[a[1]], abs_tol=1e-9)


def test_prefix_order_changes_order_only_and_filters_agree():
    tok = Tokenizer([], "abcdefghijklmnopqrstuvwxyz ")
    model = random_model(random.Random(3), len(tok.vocab))
    q = PatternQuery("(cat|dog|cow)", "(a|the) ", "all", Rules())
    texts = lambda q: {r[3] for r in run_query(q, model, tok)}
    assert texts(q) == texts(q.but(prefix_order="zero")) and len(texts(q)) == 6
    plain = PatternQuery("(cat|dog|cow)", encoding="all")
    assert texts(plain.but(preprocessors=(exclude(["cow"]),))) == texts(plain.but(preprocessors=(exclude(["cow"], deferred=True),))) == {"cat", "dog"}
    assert texts(plain.but(preprocessors=(erase(["c"]),))) == {"cat", "at", "dog", "cow", "ow"}
    assert "cats" in {"".join(p) for p in fa.enumerate_language(plain.but(preprocessors=(synonyms({"dog": ["cats"]}),)).automaton(), 5)}
    assert texts(plain) <= texts(plain.but(preprocessors=(edits(1, "abc"),)))
    assert len(list(iterate(plain, model, tok))) == 3
    assert "finite" in planner.explain(plain) and planner.choose_tier(10, 10, 1) == "driver" and planner.choose_tier(10, 10, 9) == "in_task" and planner.choose_tier(10**6, 1, 1) == "frontier"
    assert planner.defer_filters(plain.but(preprocessors=(exclude(["cow"]),))).preprocessors[0].deferred is False


def test_sampling_is_unbiased_over_prefixes_and_exact_mode_matches():
    tok = Tokenizer([], "ab")
    q = PatternQuery("", "(a|b|bb|bbb)", "all", max_tokens=8)
    dfa = lower(q, tok).dfa
    model = UniformModel(2)
    fair = Counter(tok.decode(Sampler(dfa, model, q).draw(i).tokens) for i in range(4000))
    naive = Counter(tok.decode(Sampler(dfa, model, q, weights="edge_uniform").draw(i).tokens) for i in range(4000))
    assert all(abs(n / 4000 - 0.25) < 0.03 for n in fair.values()) and len(fair) == 4
    assert abs(naive["a"] / 4000 - 0.5) < 0.03
    m = random_model(random.Random(4), 2)
    body = PatternQuery("(aa|ab|ba)", encoding="all", max_tokens=4)
    dfa = lower(body, tok).dfa
    p = {t: math.exp(m.score(tok.encode(t))) for t in ("aa", "ab", "ba")}
    exact = Counter(tok.decode(Sampler(dfa, m, body, "exact").draw(i).tokens) for i in range(6000))
    reject = Counter(tok.decode(s.tokens) for s in (Sampler(dfa, m, body, "reject").draw(i) for i in range(20000)) if s.accepted)
    masked = Counter()
    for i in range(6000):
        s = Sampler(dfa, m, body, "masked").draw(i)
        masked[tok.decode(s.tokens)] += s.weight
    for got in (exact, reject, masked):
        for t in p:
            assert abs(got[t] / sum(got.values()) - p[t] / sum(p.values())) < 0.035


def test_fit_pack_arcs_and_frontier_agree(spark):
    tok = Tokenizer([], "abc")
    texts = ["abc", "abca", "bca", "cab", "abab", "bb"]
    df = spark.createDataFrame([(list(tok.encode(t)),) for t in texts], "tokens array<int>")
    counts = fit_ngram(df, "tokens", 3).cache()
    model = CountModel.collect(counts, 3, 3)
    with pytest.raises(ModelTooLarge):
        CountModel.collect(counts, 3, 3, most=2)
    seen = Counter()
    for t in texts:
        path = [BOS, *tok.encode(t), EOS]
        for i in range(1, len(path)):
            for o in range(min(3, i + 1)):
                seen[tuple(path[i - o : i]), path[i]] += 1
    assert {(c, t): n for c, f in model.counts.items() for t, n in f.items()} == dict(seen)
    vocab = spark.createDataFrame([(t,) for t in (0, 1, 2, EOS)], "tok int")
    table = arcs(counts, 3, vocab).collect()
    for r in table[:60]:
        ctx = tuple(map(int, r["ctx"].split())) if r["ctx"] else ()
        assert math.isclose(math.log(r["p"]), model.logp(ctx, r["tok"]), rel_tol=1e-9)
        assert tuple(map(int, r["nxt"].split())) if r["nxt"] else () == model.state((*ctx, r["tok"]))
    q = PatternQuery("[abc]{2}", encoding="all", rules=Rules(top_k=3))
    dfa = lower(q, tok).dfa
    edges, finals = graph.token_edges_df(spark, {5: dfa}, tok), spark.createDataFrame([(5, s) for s in dfa.finals], "query_id long, state int")
    got = frontier_search(edges, finals, spark.createDataFrame(table), 3, 4, batch=2).orderBy("match_rank").collect()
    want = run_query(q, model, tok, 4)
    assert [r["tokens"] for r in got] == [r[2] for r in want]
    assert all(math.isclose(a["logp"], b[5], abs_tol=1e-9) for a, b in zip(got, want, strict=True))
    scored = score_batches(model, df).collect()
    assert all(math.isclose(r["logp"], model.score(tuple(r["tokens"])), abs_tol=1e-9) for r in scored)
    fn = CallableModel(lambda ctx: [0.1, 0.2, 0.3, 0.4], 3)
    assert math.isclose(math.exp(fn.logp((), 1)), 0.2) and math.isclose(math.exp(fn.logp((), EOS)), 0.4)


def test_arcs_of_the_likeliest_tokens_are_those_of_all_arcs(spark):
    rng = random.Random(11)
    rows = [([min(int(rng.expovariate(0.5)), 7) for _ in range(rng.randint(1, 6))],) for _ in range(40)]
    counts = fit_ngram(spark.createDataFrame(rows, "tokens array<int>"), "tokens", 3).cache()
    vocab = spark.createDataFrame([(t,) for t in (*range(10), EOS)], "tok int")  # 8 and 9 are never seen
    whole = {(r["ctx"], r["tok"]): r for r in arcs(counts, 3, vocab).collect()}
    assert len(whole) == 11 * counts.select("ctx").distinct().count()
    for top in (1, 3, 20):
        got = arcs(counts, 3, vocab, top).collect()
        assert {(r["ctx"], r["tok"]): (r["rnk"], round(r["p"], 12), r["nxt"]) for r in got} == {k: (r["rnk"], round(r["p"], 12), r["nxt"]) for k, r in whole.items() if r["rnk"] <= top}
        assert len(got) == len({(r["ctx"], r["tok"]) for r in got})
    got = arcs(counts, 3, vocab, 2, spark.createDataFrame([(9,), (0,), (9,)], "tok int")).collect()
    assert {(r["ctx"], r["tok"]): (r["rnk"], round(r["p"], 12), r["nxt"]) for r in got} == {
        k: (r["rnk"] if r["rnk"] <= 2 else None, round(r["p"], 12), r["nxt"]) for k, r in whole.items() if r["rnk"] <= 2 or k[1] in (0, 9)
    }


def test_frontier_of_several_queries_equals_single_searches(spark):
    tok = Tokenizer([], "abcd")
    rng = random.Random(12)
    texts = ["".join(rng.choice("aabbcd") for _ in range(rng.randint(1, 6))) for _ in range(30)]
    counts = fit_ngram(spark.createDataFrame([(list(tok.encode(t)),) for t in texts], "tokens array<int>"), "tokens", 2).cache()
    model = CountModel.collect(counts, 2, 4)
    vocab = spark.createDataFrame([(t,) for t in (*range(4), EOS)], "tok int")
    queries = {1: PatternQuery("[abcd]{3}", encoding="all", rules=Rules(top_k=3)), 2: PatternQuery("d|ca", "d?", "all", rules=Rules(top_k=3)), 3: PatternQuery("a", encoding="all", rules=Rules(top_k=3))}
    dfas = {i: lower(q, tok).dfa for i, q in queries.items()}
    edges = graph.token_edges_df(spark, dfas, tok)
    finals = spark.createDataFrame([(i, s) for i, d in dfas.items() for s in d.finals], "query_id long, state int")
    sparse = arcs(counts, 2, vocab, 3, spark.createDataFrame([(tok.encode("d")[0],)], "tok int"))
    for batch in (8, 500):
        got = frontier_search(edges, finals, sparse, 3, 12, batch=batch).orderBy("query_id", "match_rank").collect()
        want = [(i, r) for i, q in queries.items() for r in run_query(q, model, tok, 12)]
        assert Counter((r["query_id"], tuple(r["tokens"]), round(r["logp"], 9)) for r in got) == Counter((i, tuple(r[2]), round(r[5], 9)) for i, r in want)
        assert not any(r["truncated"] for r in got)


def test_matches_make_the_next_queries(spark):
    from patternlm.operators.traverse import derive, run_many

    tok = Tokenizer([], "abc ")
    model = random_model(random.Random(8), len(tok.vocab))
    first = spark.createDataFrame([(1, "a|b")], "query_id long, body string")
    build = lambda row: PatternQuery(row["body"], encoding="all")
    found = run_many(spark, first, build, model, tok, None)
    from pyspark.sql import functions as F

    after = run_many(spark, derive(found, body=F.concat("text", F.lit(" c"))), build, model, tok, None)
    assert {r["text"] for r in after.collect()} == {"a c", "b c"} and after.select("query_id").distinct().count() == 2


def test_samples_do_not_depend_on_partitions(spark):
    tok = Tokenizer([], "ab")
    q = PatternQuery("(a|b){3}", encoding="all")
    one = sample(spark, q, UniformModel(2), tok, 50).orderBy("sample_id").collect()
    assert one == sample(spark, q, UniformModel(2), tok, 50).repartition(3).orderBy("sample_id").collect()


def test_relational_walks_match_driver(spark):
    dfa = fa.compile_regex("(ab?|c)(d|e)?")
    edges, states = graph.edges_df(spark, {0: dfa})
    finals = states.where("is_final").select("query_id", "state")
    got = {(r["state"], r["len"]): int(r["n"]) for r in walks.walks_by_length(edges, finals, 3).collect()}
    want = fa.walks_by_length(dfa, 3)
    assert got == {(s, n): w for n, row in enumerate(want) for s, w in enumerate(row) if w}


def test_chi_squared_tail_and_measures(spark):
    for stat, dof, p in ((3.841458820694124, 1, 0.05), (16.918977604620448, 9, 0.05), (27.877164871256568, 9, 0.001)):
        assert math.isclose(10 ** measures.chi2_sf_log10(stat, dof), p, rel_tol=1e-9)
    assert math.isclose(measures.chi2_sf_log10(1060, 2), -530 / math.log(10), rel_tol=1e-12)  # far below the smallest double of p
    t = spark.createDataFrame([("a", "x", 10), ("a", "y", 20), ("b", "x", 20), ("b", "y", 10)], "x string, y string, n long")
    row = measures.chi2(t, "x", "y").first()
    assert math.isclose(row["stat"], 20 / 3, rel_tol=1e-6) and row["dof"] == 1 and row["total"] == 60
    assert measures.per_outcome(t, "x", "y").count() == 2
    m = spark.createDataFrame([(1, 1, [1], "a", 1.0, -1.0, "", "a", True, 0, 1, 1), (1, 2, [2], "b", 1.0, -1.0, "", "b", False, 1, 1, 1)], MATCHES)
    qs = spark.createDataFrame([(1,), (2,)], "query_id long")
    assert measures.success_rate(m, qs).first()["success"] == 0.5
    assert measures.volume(m, 1).first()["volume"] == 1
    assert measures.edit_encoding_cube(m).where("edited IS NULL AND canonical IS NULL").first()["n"] == 2
    assert measures.edit_false_positives(m, ["a"]).first()["false_positives"] == 1.0
    assert measures.truth_rank(m, spark.createDataFrame([("b",)], "text string"), ["text"]).first()["match_rank"] == 2
    assert measures.amplification(6.0, 2.0) == 3.0 and measures.amplification(1.0, 0.0) == math.inf


def test_final_states_that_go_on_stop_in_proportion():
    """a, b, bb, bbb without an end token: every string by its own probability, exactly or by weight."""
    tok = Tokenizer([], "ab")
    q = PatternQuery("a|b|bb|bbb", encoding="all", max_tokens=8)
    dfa, model = lower(q, tok).dfa, random_model(random.Random(4), 2)
    p = {t: math.exp(model.score(tok.encode(t))) for t in ("a", "b", "bb", "bbb")}
    exact, masked, reject = Counter(), Counter(), Counter()
    for i in range(8000):
        exact[tok.decode(Sampler(dfa, model, q, "exact").draw(i).tokens)] += 1
    for got, mode in ((masked, "masked"), (reject, "reject")):
        sampler = Sampler(dfa, model, q, mode)
        for i in range(30000):
            s = sampler.draw(i)
            got[tok.decode(s.tokens)] += s.weight if s.accepted else 0
    for got in (exact, masked, reject):
        for t in p:
            assert abs(got[t] / sum(got.values()) - p[t] / sum(p.values())) < 0.03, (t, got)


def test_canonical_samples_are_canonical():
    from patternlm.functions.tokenizer import Tokenizer as Merges

    tok = Merges([("a", "b"), ("ab", "c"), ("b", "c")], "abc")
    q = PatternQuery("(abc|bc|cab|abab)c?", max_tokens=8)
    full = lower(q.but(encoding="all"), tok).dfa
    model = random_model(random.Random(5), len(tok.vocab))
    sampler = Sampler(full, model, q, "exact", check=tok.is_canonical, pair=graph.pair_check(tok))
    drawn = [sampler.draw(i) for i in range(300)]
    assert all(tok.is_canonical(s.tokens) for s in drawn if s.accepted) and sum(s.accepted for s in drawn) > 250


def test_traversals_are_pluggable():
    from patternlm.operators import traverse

    tok = Tokenizer([], "ab")
    model = random_model(random.Random(6), 2)
    q = PatternQuery("(a|b){2}", encoding="all")
    assert [r[3] for r in run_query(q.but(traversal="beam"), model, tok, 2)] == [r[3] for r in run_query(q, model, tok, 2)]
    assert len(run_query(q.but(traversal="sample"), model, tok, 7)) == 7
    traverse.register_traversal("worst", lambda *a, **o: reversed(list(traverse.TRAVERSALS["best"](a[0], a[1], a[2], None, **o))))
    assert [r[3] for r in run_query(q.but(traversal="worst"), model, tok)] == [r[3] for r in run_query(q, model, tok)][::-1]
    with pytest.raises(ValueError):
        run_query(q.but(traversal="none"), model, tok)


def test_batched_models_are_asked_for_many_contexts_at_once(spark):
    tok = Tokenizer([], "abc")
    m = random_model(random.Random(7), 3)
    p = lambda ctx: [math.exp(m.logp(ctx, t)) for t in (0, 1, 2, EOS)]
    one, many = CallableModel(p, 3), CallableModel(lambda ctxs: [p(c) for c in ctxs], 3, batched=True)
    q = PatternQuery("[abc]{3}", encoding="all", rules=Rules(top_k=3))
    assert [r[2] for r in run_query(q, one, tok, 9)] == [r[2] for r in run_query(q, many, tok, 9, ahead=8)]
    assert many.calls < one.calls / 2
    df = spark.createDataFrame([([0, 1, 2],), ([2, 2],)], "tokens array<int>")
    rows = score_batches(CallableModel(lambda ctxs: [[0.1, 0.2, 0.3, 0.4] for _ in ctxs], 3, batched=True), df).collect()
    assert sorted(round(math.exp(r["logp"]), 9) for r in rows) == [0.006, 0.09]
    got = measures.run_metrics(q, many, tok, 5)
    assert got["results"] == 5 and 0 < got["first_result_sec"] <= got["sec"] and 0 < got["busy_share"] <= 1 and got["lookups"] > 0


def test_frontier_says_when_it_was_stopped(spark):
    tok = Tokenizer([], "ab")
    dfa = lower(PatternQuery("(a|b){3}", encoding="all"), tok).dfa
    edges, finals = graph.token_edges_df(spark, {0: dfa}, tok), spark.createDataFrame([(0, s) for s in dfa.finals], "query_id long, state int")
    counts = fit_ngram(spark.createDataFrame([([0, 1, 0],), ([1, 1],)], "tokens array<int>"), "tokens", 2)
    table = spark.createDataFrame(arcs(counts, 2, spark.createDataFrame([(t,) for t in (0, 1, EOS)], "tok int")).collect())
    whole = frontier_search(edges, finals, table, None, 8, batch=3).collect()
    assert len(whole) == 8 and not any(r["truncated"] for r in whole)
    short = frontier_search(edges, finals, table, None, 8, batch=3, max_rounds=4).collect()
    assert all(r["truncated"] for r in short) and len(short) < 8



def test_prefix_edits_are_uniform_by_walks_and_early_by_edges(spark):
    from patternlm.queries import experiments as ex

    got = {r["weights"]: r["first_six"] for r in ex.q_prefix_edit_pos(spark, "").collect()}
    assert got["edge_uniform"] > 0.8 and got["walks"] < 0.35


def test_log_of_a_sum(spark):
    rows = [("a", x) for x in (-1000.0, -999.5, -1200.0, -300.0 * 3 - 0.001)] + [("b", -math.inf), ("c", -math.inf), ("c", 2.0), ("d", 700.0), ("d", 710.0), ("e", None)]
    got = {r["g"]: r["log_sum"] for r in measures.log_sum_exp(spark.createDataFrame(rows, "g string, v double"), "v", ["g"]).collect()}
    assert set(got) == set("abcd") and got["b"] == -math.inf and math.isclose(got["c"], 2)
    assert math.isclose(got["a"], -900.001 + math.log(1 + math.exp(-99.999) + math.exp(-99.499)), rel_tol=1e-12)
    assert math.isclose(got["d"], 710 + math.log(1 + math.exp(-10)), rel_tol=1e-12)


def test_row_samples_are_seeded(spark):
    from patternlm.sources.io import sample_rows

    rows = spark.range(20_000)
    some = {r["id"] for r in sample_rows(rows, "id", 0.2).collect()}
    assert some == {r["id"] for r in sample_rows(rows.repartition(7), "id", 0.2).collect()} != {r["id"] for r in sample_rows(rows, "id", 0.2, seed=1).collect()}
    assert abs(len(some) - 4000) < 300 and sample_rows(rows, "id", 0.0).isEmpty() and sample_rows(rows, "id", 1.0).count() == 20_000


def test_closed_choices_are_ranked_as_a_search_ranks_them(spark):
    from patternlm.plans import workloads as wl

    facts = [(0, "1995-03-05", "March 5, 1995"), (0, "1996-04-07", "April 7, 1996"), (1, "1997-03-07", "March 7, 1997"), (2, "1995-03-05", "March 5, 1995"), (4, "1996-12-01", "December 1, 1996")]
    said = spark.createDataFrame([(k, x, f"Customer {k} ordered on {s}") for k, x, s in facts], "c_custkey long, order_date string, sentence string")
    choices = wl.closed_choices(said, 3)
    of = {}
    for r in choices.collect():
        of.setdefault(r["query_id"], {})[r["choice"]] = r["is_truth"]
    assert of == {
        0: {" March 5, 1995": True, " March 7, 1997": False},
        1: {" March 7, 1997": True, " March 5, 1995": False, " December 1, 1996": False},
        2: {" March 5, 1995": True, " December 1, 1996": False},
        4: {" December 1, 1996": True, " March 5, 1995": False, " March 7, 1997": False},
    }
    model, tok = wl.chunk_model(said, "sentence", 5)
    for r in of:
        got = wl.score_choices(choices.where(f"query_id = {r}"), model, tok).orderBy("rnk").collect()
        want = run_query(PatternQuery("|".join(sorted(of[r])), f"Customer {r} ordered on", "all", prefix_order="zero"), model, tok)
        assert [x["choice"] for x in got] == [m[7] for m in want]
        ctx = (BOS, *tok.encode(f"Customer {r} ordered on"))
        assert all(math.isclose(x["logp"], model.score(tok.encode(x["choice"]), ctx)) for x in got)
    longer = spark.createDataFrame([(1, "Customer 1 ordered on", c) for c in (" March", " March 7, 1997", " April 7, 1996")], "query_id long, prompt string, choice string")
    for key, rank in ((lambda x: (-x["logp"], x["choice"]), "rnk"), (lambda x: (-x["logp"] / x["n_tokens"], x["choice"]), "mean_rnk")):
        got = wl.score_choices(longer, model, tok).collect()
        assert [x["choice"] for x in sorted(got, key=key)] == [x["choice"] for x in sorted(got, key=lambda x: x[rank])]
    sheets = {r["query_id"]: (r["prompt"], r["answer"]) for r in wl.answer_sheets(choices).collect()}
    assert sheets[0] == ("Customer 0 ordered on A) March 5, 1995 B) March 7, 1997 Answer:", " A") and sheets[1][1] == " C" and sheets[4][1] == " A"
