"""Count models, next-token distributions, scores and decision rules."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from patternlm.functions import automata as fa
from patternlm.functions.tokenizer import Tokenizer
from patternlm.operators import graph
from patternlm.operators import wordmodel as wm
from patternlm.operators.model import CountModel, TableModel
from patternlm.plans.query import PatternQuery, Rules
from patternlm.queries import query
from patternlm.sources.io import table

SEQ = r"""seq AS (SELECT list_append(w, '</s>') AS w FROM (SELECT regexp_extract_all(lower(trim(s)), '[a-z]+') AS w FROM (SELECT unnest(regexp_split_to_array(text, '[.!?\n|]')) AS s FROM documents WHERE lang = 'en')) WHERE len(w) > 0)"""
UNI = "uni AS (SELECT w, count(*) AS n FROM (SELECT unnest(w) AS w FROM seq) GROUP BY w)"
BI = "bi AS (SELECT c1, w, count(*) AS n FROM (SELECT unnest(w[1 : len(w) - 1]) AS c1, unnest(w[2 : len(w)]) AS w FROM seq WHERE len(w) >= 2) GROUP BY ALL)"
TRI = "tri AS (SELECT c2, c1, w, count(*) AS n FROM (SELECT unnest(w[1 : len(w) - 2]) AS c2, unnest(w[2 : len(w) - 1]) AS c1, unnest(w[3 : len(w)]) AS w FROM seq WHERE len(w) >= 3) GROUP BY ALL)"
PROBS = """tot AS (SELECT sum(n) AS big_n, count(*) AS big_d FROM uni), bc AS (SELECT c1, sum(n) AS n1, count(*) AS d1 FROM bi GROUP BY c1)"""
PROBS3 = PROBS + ", tc AS (SELECT c2, c1, sum(n) AS n2c, count(*) AS d2c FROM tri GROUP BY ALL)"


def p_sql(rows: str, order: int) -> str:
    """rows (c2, c1, w, ...) with p."""
    p1 = "(coalesce(uni.n, 0) + big_d / (big_d + 1)) / (big_n + big_d)"
    p2 = f"CASE WHEN n1 IS NULL THEN {p1} ELSE (coalesce(bi.n, 0) + d1 * ({p1})) / (n1 + d1) END"
    p3 = f"CASE WHEN n2c IS NULL THEN {p2} ELSE (coalesce(tri.n, 0) + d2c * ({p2})) / (n2c + d2c) END"
    more = "LEFT JOIN tc ON tc.c2 = r.c2 AND tc.c1 = r.c1 LEFT JOIN tri ON tri.c2 = r.c2 AND tri.c1 = r.c1 AND tri.w = r.w" if order == 3 else ""
    return f"SELECT r.*, {p3 if order == 3 else p2} AS p FROM {rows} r CROSS JOIN tot LEFT JOIN uni ON uni.w = r.w LEFT JOIN bc ON bc.c1 = r.c1 LEFT JOIN bi ON bi.c1 = r.c1 AND bi.w = r.w {more}"


def seq(spark, d):
    return wm.sentence_words(table(spark, d, "documents"))


@query(f"WITH {SEQ}, {UNI} SELECT w, n FROM uni")
def q_lm_unigram(spark, d):
    return wm.grams(seq(spark, d), 1)


@query(f"WITH {SEQ}, {BI} SELECT c1, w, n FROM bi")
def q_lm_bigram(spark, d):
    return wm.grams(seq(spark, d), 2)


@query(f"WITH {SEQ}, {TRI} SELECT c2, c1, w, n FROM tri")
def q_lm_trigram(spark, d):
    return wm.grams(seq(spark, d), 3)


def ranked(spark, d):
    return wm.grams(seq(spark, d), 2).withColumn("rnk", F.row_number().over(Window.partitionBy("c1").orderBy(F.desc("n"), "w")))


RANKED = f"WITH {SEQ}, {BI}, r AS (SELECT *, row_number() OVER (PARTITION BY c1 ORDER BY n DESC, w) AS rnk FROM bi)"


@query(f"{RANKED} SELECT c1, w, n, CAST(rnk AS INT) AS rnk FROM r WHERE rnk <= 3")
def q_next_token(spark, d):
    return ranked(spark, d).where("rnk <= 3")


@query(f"{RANKED} SELECT c1, string_agg(w, ' ' ORDER BY rnk) AS best FROM r WHERE rnk <= 5 GROUP BY c1")
def q_topk_packed(spark, d):
    """A packed array of the best followers of each context."""
    top = ranked(spark, d).where("rnk <= 5").groupBy("c1").agg(F.sort_array(F.collect_list(F.struct("rnk", "w"))).alias("best"))
    return top.select("c1", F.array_join(F.transform("best", lambda s: s["w"]), " ").alias("best"))


@query(f"{RANKED} SELECT count(*) AS without_rules, count(*) FILTER (WHERE rnk <= 40) AS with_rules FROM r")
def q_topk_prune(spark, d):
    from patternlm.operators.measures import rule_effect

    r = ranked(spark, d)
    return rule_effect(r, r.where("rnk <= 40"))


@query(f"""{RANKED}, t AS (SELECT c1, w, n, sum(n) OVER (PARTITION BY c1) AS tot, coalesce(sum(n) OVER (PARTITION BY c1 ORDER BY rnk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM r)
SELECT c1, count(*) AS kept FROM t WHERE 2 * before < tot GROUP BY c1""")
def q_topp(spark, d):
    """Top-p 0.5: followers until their shares reach a half."""
    w = Window.partitionBy("c1").orderBy("rnk")
    t = ranked(spark, d).withColumn("tot", F.sum("n").over(Window.partitionBy("c1"))).withColumn("before", F.coalesce(F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return t.where("2 * before < tot").groupBy("c1").agg(F.count("*").alias("kept"))


BENCH_WORDS = "b AS (SELECT item_id, regexp_extract_all(lower(text), '[a-z]+') AS w FROM benchmark)"


@query(f"""WITH {SEQ}, {UNI}, {BI}, {TRI}, {PROBS3}, {BENCH_WORDS},
g AS (SELECT item_id, unnest(w[1 : len(w) - 2]) AS c2, unnest(w[2 : len(w) - 1]) AS c1, unnest(w[3 : len(w)]) AS w FROM b WHERE len(w) >= 3)
SELECT item_id, count(*) AS words, round(sum(ln(p)), 4) AS logp FROM ({p_sql("g", 3)}) GROUP BY item_id""")
def q_score(spark, d):
    """Log probability of benchmark passages, word by word after the first two."""
    b = table(spark, d, "benchmark").select("item_id", F.expr("regexp_extract_all(lower(text), '[a-z]+', 0)").alias("w")).where(F.size("w") >= 3)
    runs = F.transform(F.sequence(F.lit(0), F.size("w") - 3), lambda i: F.struct(F.get("w", i).alias("c2"), F.get("w", i + 1).alias("c1"), F.get("w", i + 2).alias("w")))
    rows = b.select("item_id", F.explode(runs).alias("g")).select("item_id", "g.*")
    return wm.fit(seq(spark, d), 3).score(rows).groupBy("item_id").agg(F.count("*").alias("words"), F.round(F.sum(F.log("p")), 4).alias("logp"))


# -- the worked example of six tokens -------------------------------------------------------------------------------------------------

SIX = Tokenizer([], vocab={t: i for i, t in enumerate(("T", "h", "e", "Th", "he", "The"))})
T_, H_, E_, TH, HE, THE = range(6)
TABLE = TableModel({(): {THE: 0.6, TH: 0.3, T_: 0.1}, (TH,): {E_: 0.9, H_: 0.06, T_: 0.04}, (T_,): {H_: 0.5, HE: 0.5}, (T_, H_): {E_: 1.0}}, 6)


def six(spark, rules, model=TABLE):
    from patternlm.operators.traverse import MATCHES, run_query

    q = PatternQuery("The", encoding="all", rules=rules)
    return spark.createDataFrame(run_query(q, model, SIX), MATCHES).select("match_rank", F.array_join(F.transform("tokens", lambda t: F.element_at(F.array(*map(F.lit, SIX.vocab)), t + 1)), "|").alias("path"), F.round(F.exp("logp"), 6).alias("p"))


COUNTED = f"""v AS (SELECT * FROM (VALUES {", ".join(f"('{t}')" for t in SIX.vocab)}) AS v(token)),
n AS (SELECT token, CAST((SELECT sum((length(text) - length(replace(text, token, ''))) // length(token)) FROM documents WHERE lang = 'en') AS BIGINT) AS n FROM v),
p AS (SELECT token, (n + d / 7) / (s + d) AS p FROM n, (SELECT sum(n) AS s, count(*) FILTER (WHERE n > 0) AS d FROM n))"""


def six_counted(spark, d):
    """A model of the six tokens by how often each stands in the English texts."""
    text = table(spark, d, "documents").where("lang = 'en'").select("text")
    times = lambda t: F.coalesce(F.sum((F.length("text") - F.length(F.replace("text", F.lit(t), F.lit("")))) / len(t)), F.lit(0)).cast("long")
    found = text.agg(*(times(t).alias(f"n{i}") for t, i in SIX.vocab.items())).first()
    seen = {i: found[f"n{i}"] for i in SIX.vocab.values() if found[f"n{i}"]}
    return CountModel({(): seen} if seen else {}, 1, len(SIX.vocab))


@query(f"""WITH RECURSIVE {COUNTED}, r AS (SELECT 'The' AS word, 1 AS pos, '' AS path, 1.0::DOUBLE AS q UNION ALL
SELECT word, pos + length(token), CASE WHEN path = '' THEN token ELSE path || '|' || token END, q * p FROM r JOIN p ON substring(word, pos, length(token)) = token)
SELECT row_number() OVER (ORDER BY q DESC, path) AS match_rank, path, round(q, 6) AS p FROM r WHERE pos = length(word) + 1""")
def q_enc_all(spark, d):
    """All four encodings of a three-letter word, likeliest first."""
    return six(spark, Rules(), six_counted(spark, d))


@query("SELECT * FROM (VALUES (CAST(1 AS BIGINT), 'The', 0.6::DOUBLE), (2, 'Th|e', 0.27)) AS v(match_rank, path, p)")
def q_enc_topk(spark, d):
    """Two of them under top-k 2."""
    return six(spark, Rules(top_k=2))


@query(f"WITH {COUNTED} SELECT 'Th|e' AS a, 'The' AS b, round((SELECT p FROM p WHERE token = 'Th') * (SELECT p FROM p WHERE token = 'e') / (SELECT p FROM p WHERE token = 'The'), 6) AS ratio")
def q_enc_ratio(spark, d):
    from patternlm.operators.measures import encoding_ratio

    return spark.createDataFrame([("Th|e", "The", round(encoding_ratio(six_counted(spark, d), (TH, E_), (THE,), ()), 6))], "a string, b string, ratio double")


@query("SELECT count(*) AS n, round(3 / 4, 6)::DOUBLE AS rate FROM (VALUES (1), (2), (3), (4)) AS v(x)")
def q_noncanon_rate(spark, d):
    """Share of encodings of the worked example that are not the tokenizer's own."""
    from patternlm.operators.measures import noncanonical_rate

    tok = Tokenizer([("T", "h"), ("Th", "e"), ("h", "e")], "The", vocab=SIX.vocab)
    full = list(fa.enumerate_language(graph.compile_full(fa.words_dfa(["The"]), SIX), 3))
    return noncanonical_rate(spark.createDataFrame([(tok.is_canonical(p),) for p in full], "is_canonical boolean"))


@query("SELECT * FROM (VALUES ('a', 0.25::DOUBLE), ('b', 0.1875), ('bb', 0.5625)) AS v(text, p)")
def q_eos(spark, d):
    """The end token decides between a string and its continuation: p(a) 1/4, then b stops with 1/4."""
    from patternlm.functions.tokenizer import EOS
    from patternlm.operators.traverse import MATCHES, run_query

    tok = Tokenizer([], "ab")
    model = TableModel({(): {0: 0.25, 1: 0.75}, (0,): {EOS: 1.0}, (1,): {EOS: 0.25, 1: 0.75}, (1, 1): {EOS: 1.0}}, 2)
    rows = run_query(PatternQuery("a|b|bb", encoding="all", require_eos=True), model, tok)
    return spark.createDataFrame(rows, MATCHES).select("text", F.round(F.exp("logp"), 6).alias("p"))
