"""The experiments: co-occurrence bias, toxic extraction, last words, dates."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F

from patternlm.operators import measures as ms
from patternlm.operators import wordmodel as wm
from patternlm.operators.traverse import MATCHES, counted, run_many, run_query, sample, successes, tasks
from patternlm.plans import workloads as wl
from patternlm.plans.query import PatternQuery, edits
from patternlm.queries import query
from patternlm.queries.corpus import SENTENCES, SIX
from patternlm.queries.models import BI, PROBS, PROBS3, SEQ, TRI, UNI, p_sql
from patternlm.session import cut
from patternlm.sources.io import INSULTS, english_words, sentences, table, verbalised_orders

# -- bias -----------------------------------------------------------------------------------------------------------------------------


def listed(words) -> str:
    return ", ".join(f"'{w}'" for w in words)


PAIRS = f"""pairs AS (SELECT x, y, count(*) AS n FROM (SELECT unnest(w[1 : len(w) - 1]) AS x, unnest(w[2 : len(w)]) AS y FROM (SELECT regexp_extract_all(lower(text), '[a-z]+') AS w FROM documents WHERE lang = 'en') WHERE len(w) >= 2)
WHERE x IN ({listed(wl.GROUPS)}) AND y IN ({listed(wl.OUTCOMES)}) GROUP BY ALL)"""
CHI = """c AS (SELECT {g}x, y, n, sum(n) OVER (PARTITION BY {p}x) AS r, sum(n) OVER (PARTITION BY {p}y) AS k, sum(n) OVER ({w}) AS t FROM {0})"""


@query("""WITH w AS (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS w FROM documents WHERE lang = 'en'), c AS (SELECT w, count(*) AS n FROM w GROUP BY w)
SELECT length(w) AS n_letters, round(ln(sum(n) / (SELECT sum(n) FROM c)), 6) AS log_mass FROM c GROUP BY n_letters""")
def q_log_mass(spark, d):
    """The log mass of words by length, from log probabilities alone."""
    counts = english_words(table(spark, d, "documents")).select(F.explode("w").alias("w")).groupBy("w").agg(F.count("*").alias("n"))
    logs = counts.select(F.length("w").cast("long").alias("n_letters"), F.log(F.col("n") / counts.agg(F.sum("n")).scalar()).alias("logp"))
    return ms.log_sum_exp(logs, "logp", ["n_letters"]).select("n_letters", F.round("log_sum", 6).alias("log_mass"))


def pairs(spark, d):
    return wl.slot_pairs(table(spark, d, "documents"))


@query(f"WITH {PAIRS} SELECT x, y, n, round(n / sum(n) OVER (PARTITION BY x), 6) AS p FROM pairs")
def q_bias_cond(spark, d):
    return ms.cond_dist(pairs(spark, d), "x", "y", F.col("n"))


@query(f"WITH {PAIRS} SELECT y, CAST(coalesce(sum(n) FILTER (WHERE x = 'this'), 0) AS BIGINT) AS this, CAST(coalesce(sum(n) FILTER (WHERE x = 'that'), 0) AS BIGINT) AS that FROM pairs GROUP BY y")
def q_chi2_table(spark, d):
    return pairs(spark, d).groupBy("y").pivot("x", list(wl.GROUPS)).agg(F.sum("n")).fillna(0)


@query(f"""WITH {PAIRS}, {CHI.format("pairs", g="", p="", w="")} SELECT round(sum((n - r * k / t) * (n - r * k / t) / (r * k / t)), 6) AS stat, CAST((count(DISTINCT x) - 1) * (count(DISTINCT y) - 1) AS BIGINT) AS dof, CAST(sum(n) AS BIGINT) AS total FROM c""")
def q_chi2(spark, d):
    """Omnibus test of group against outcome."""
    return ms.chi2_parts(pairs(spark, d), "x", "y")


@query()
def q_chi2_log10p(spark, d):
    """The same with log10 p, and each outcome against the others."""
    t = pairs(spark, d)
    every = ms.chi2(t, "x", "y").withColumn("outcome", F.lit("all"))
    return every.unionByName(ms.per_outcome(t, "x", "y"))


@query("""WITH p AS (SELECT string_split(p_name, ' ')[1] AS x, string_split(p_name, ' ')[2] AS y FROM part), n AS (SELECT x, y, count(*) AS n FROM p WHERE x IN ('hot', 'cold') GROUP BY ALL),
c AS (SELECT x, y, n, sum(n) OVER (PARTITION BY x) AS r, sum(n) OVER (PARTITION BY y) AS k, sum(n) OVER () AS t FROM n)
SELECT round(sum((n - r * k / t) * (n - r * k / t) / (r * k / t)), 6) AS stat, CAST((count(DISTINCT x) - 1) * (count(DISTINCT y) - 1) AS BIGINT) AS dof, CAST(sum(n) AS BIGINT) AS total FROM c""")
def q_chi2_null(spark, d):
    """A null case: adjectives against nouns of part names."""
    w = F.split("p_name", " ")
    n = table(spark, d, "part").select(w[0].alias("x"), w[1].alias("y")).where(F.col("x").isin("hot", "cold")).groupBy("x", "y").agg(F.count("*").alias("n"))
    return ms.chi2_parts(n, "x", "y")


@query("""WITH n AS (SELECT o_orderstatus AS x, o_orderpriority AS y, count(*) AS n FROM orders GROUP BY ALL), c AS (SELECT x, y, n, sum(n) OVER (PARTITION BY x) AS r, sum(n) OVER (PARTITION BY y) AS k, sum(n) OVER () AS t FROM n)
SELECT round(sum((n - r * k / t) * (n - r * k / t) / (r * k / t)), 6) AS stat, CAST((count(DISTINCT x) - 1) * (count(DISTINCT y) - 1) AS BIGINT) AS dof, CAST(sum(n) AS BIGINT) AS total FROM c""")
def q_chi2_orders(spark, d):
    n = table(spark, d, "orders").groupBy(F.col("o_orderstatus").alias("x"), F.col("o_orderpriority").alias("y")).agg(F.count("*").alias("n"))
    return ms.chi2_parts(n, "x", "y")


SLOT = f"""slot AS (SELECT '' AS c2, x AS c1, y AS w FROM (SELECT unnest([{listed(wl.GROUPS)}]) AS x), (SELECT unnest([{listed(wl.OUTCOMES)}]) AS y)), q AS ({p_sql("slot", 2)})"""
STRATA = "CAST(floor(hi * {n} + 0.5) - floor((hi - s) * {n} + 0.5) AS BIGINT) AS n"


def slot_probabilities(spark, d):
    rows = spark.createDataFrame([("", x, y) for x in wl.GROUPS for y in wl.OUTCOMES], "c2 string, c1 string, w string")
    return wm.fit(wm.sentence_words(table(spark, d, "documents")), 2).score(rows)


def stratified(rows, by, n, p):
    """Counts of n stratified draws (u = (i + 1/2) / n) of p over each group of by."""
    from pyspark.sql import Window

    g = Window.partitionBy(*by)
    hi = F.sum(p).over(g.orderBy("c1", "w").rowsBetween(Window.unboundedPreceding, 0)) / F.sum(p).over(g)
    rows = rows.withColumn("hi", F.round(hi, 9)).withColumn("s", F.round(F.col(p) / F.sum(p).over(g), 9))
    lo = F.coalesce(F.lag("hi").over(g.orderBy("c1", "w")), F.lit(0.0))
    return rows.withColumn("n", (F.floor(F.col("hi") * n + 0.5) - F.floor(lo * n + 0.5)).cast("long"))


def strata_sql(by: str, n: int, p: str, source: str) -> str:
    part = f"PARTITION BY {by}" if by else ""
    return f"""st AS (SELECT *, round(sum({p}) OVER ({part} ORDER BY c1, w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) / sum({p}) OVER ({part}), 9) AS hi FROM {source}),
sn AS (SELECT c1 AS x, w AS y, CAST(floor(hi * {n} + 0.5) - floor(coalesce(lag(hi) OVER ({part} ORDER BY c1, w), 0.0) * {n} + 0.5) AS BIGINT) AS n FROM st)"""


@query(f"WITH {SEQ}, {UNI}, {BI}, {PROBS}, {SLOT}, {strata_sql('c1', 5000, 'p', 'q')} SELECT x, y, n FROM sn")
def q_bias_canon_prefix(spark, d):
    """5,000 draws for each group, the group as prefix."""
    return stratified(slot_probabilities(spark, d), ["c1"], 5000, "p").select(F.col("c1").alias("x"), F.col("w").alias("y"), "n")


@query(f"""WITH {SEQ}, {UNI}, {BI}, {PROBS}, {SLOT}, gx AS (SELECT '' AS c2, '</s>' AS c1, x AS w FROM (SELECT unnest([{listed(wl.GROUPS)}]) AS x)), px AS ({p_sql("gx", 2)}),
j AS (SELECT q.c1, q.w, q.p * px.p AS pj FROM q JOIN px ON px.w = q.c1), {strata_sql('', 10000, 'pj', 'j')} SELECT x, y, n FROM sn""")
def q_bias_all_noprefix(spark, d):
    """10,000 draws of the whole template without a prefix: the model chooses the group too."""
    slots = slot_probabilities(spark, d)
    heads = wm.fit(wm.sentence_words(table(spark, d, "documents")), 2).score(spark.createDataFrame([("", wm.END, x) for x in wl.GROUPS], "c2 string, c1 string, w string"))
    joint = slots.join(heads.select(F.col("w").alias("c1"), F.col("p").alias("px")), "c1").withColumn("pj", F.col("p") * F.col("px"))
    return stratified(joint, [F.lit(1)], 10000, "pj").select(F.col("c1").alias("x"), F.col("w").alias("y"), "n")


def _characters(spark, d, order):
    """A character model of all English sentences."""
    s = sentences(table(spark, d, "documents").where("lang = 'en'")).select(F.lower("sentence").alias("s"))
    return wl.character_model(s, "s", order)


PER_GROUP = 5000


def bias_samples(spark, d, prefix, n_edits, n=PER_GROUP, order=5, mode="masked", fitted=None, encoding="all"):
    """n samples for each group: with the group as prefix, or n times the groups of the whole template, where the model chooses the group."""
    model, tok = fitted or _characters(spark, d, order)
    if not prefix:
        return sample(spark, wl.bias_query(encoding, False, n_edits), model, tok, n * len(wl.GROUPS), mode)
    out = None
    for i, x in enumerate(wl.GROUPS):
        q = wl.bias_query(encoding, True, n_edits, (x,))
        own = sample(spark, q.but(seed=q.seed + i), model, tok, n, mode).withColumn("x", F.lit(x))  # a seed each: groups are independent
        out = own if out is None else out.unionByName(own)
    return out


def tagged(samples):
    """Group and outcome of a sample: those of the template nearest by edits (ties: by text), of the sample's own group where it was given one."""
    given = "x" in samples.columns
    near = [F.struct((F.levenshtein("text", F.lit(f"{x} {y}")) + (F.when(F.col("x") == x, 0).otherwise(1000) if given else F.lit(0))).alias("k"), F.lit(x).alias("x"), F.lit(y).alias("y")) for x in wl.GROUPS for y in wl.OUTCOMES]
    best = samples.withColumn("best", F.array_min(F.array(*near)))
    return best.withColumn("x", F.col("best.x")).withColumn("y", F.col("best.y")).withColumn("distance", F.col("best.k"))


@query()
def q_bias_edits(spark, d):
    """Samples of the template within one edit, by group and edits from the nearest template."""
    s = tagged(bias_samples(spark, d, True, 1))
    return s.groupBy("x", "distance").agg(F.count("*").alias("n"))


@query()
def q_bias_grid(spark, d):
    """Statistic and log10 p by setting: encoding, prefix, edits, model order; draws of a model of a public tokenizer's tokens, where encodings differ."""
    out, fitted = None, {order: _toxic_model(spark, d, order) for order in (3, 2)}
    for encoding in ("canonical", "all"):
        for prefix in (True, False):
            for n_edits in (0, 1):
                for order in (3, 2):
                    s = bias_samples(spark, d, prefix, n_edits, fitted=fitted[order], encoding=encoding).where("accepted")
                    cell = ms.chi2(tagged(s).groupBy("x", "y").agg(F.count("*").alias("n")), "x", "y")
                    cell = cell.select(F.lit(encoding).alias("encoding"), F.lit(prefix).alias("prefix"), F.lit(n_edits).alias("edits"), F.lit(order).alias("model_order"), "stat", "dof", "total", "log10_p")
                    out = cell if out is None else out.unionByName(cell)
    return out


LONG_PREFIX = "it was said of (this|that) one "


@query()
def q_prefix_edit_pos(spark, d):
    """Where one edit of a long prefix falls in 5,000 draws: by walks (uniform over prefixes) and by edges (early ones favoured)."""
    from patternlm.functions.tokenizer import Tokenizer
    from patternlm.operators.model import UniformModel

    letters = "abcdefghijklmnopqrstuvwxyz "
    tok = Tokenizer([], letters)
    q = PatternQuery("end", LONG_PREFIX, "all", preprocessors=(edits(1, letters, "prefix"),))
    out = None
    for weights in ("walks", "edge_uniform"):
        s = sample(spark, q, UniformModel(len(letters)), tok, PER_GROUP, weights=weights)
        near = F.array_min(F.array(*(F.struct(F.levenshtein("prefix_text", F.lit(LONG_PREFIX.replace("(this|that)", x))).alias("k"), F.lit(LONG_PREFIX.replace("(this|that)", x)).alias("t")) for x in wl.GROUPS)))
        edited = s.withColumn("near", near).where("near.k = 1").select(F.col("near.t").alias("w"), F.col("prefix_text").alias("t"))
        at = ms.edit_positions(edited, "w", "t").agg(F.sum("n").alias("edits"), F.round(F.sum(F.when(F.col("edit_pos") <= 6, F.col("n")).otherwise(0)) / F.sum("n"), 6).alias("first_six"))
        at = at.select(F.lit(weights).alias("weights"), "edits", "first_six")
        out = at if out is None else out.unionByName(at)
    return out


# -- toxic extraction -------------------------------------------------------------------------------------------------------------------

CAP = 1000  # results counted per input, at most

def _toxic_model(spark, d, order):
    """A token model of English sentences over a public tokenizer's ids."""
    import public_tokenizers

    tok = wl.PublicTokenizer(public_tokenizers.path("byte_bpe_50k.json"))
    text = sentences(table(spark, d, "documents").where("lang = 'en'")).select("sentence")
    return wl.token_model(spark, text, "sentence", tok, order), tok


def toxic_run(spark, d, mode="prompted", encoding="canonical", n_edits=0, order=3, limit=1, fitted=None, inputs=None):
    """Matches of each input; every search goes on until its limit is reached or its language is exhausted."""
    model, tok = fitted or _toxic_model(spark, d, order)
    inputs = wl.toxic_inputs(spark, d) if inputs is None else inputs

    def build(row):
        return wl.toxic_query(row, mode, encoding, n_edits)

    return run_many(spark, inputs, build, model, tok, limit), inputs


@query(f"""WITH {SENTENCES}, h AS (SELECT DISTINCT sentence, regexp_extract(sentence, '{SIX}', 2) AS hit FROM sent JOIN documents USING (doc_id) WHERE lang = 'en' AND regexp_matches(sentence, '{SIX}'))
SELECT hit, count(*) AS inputs FROM h GROUP BY hit""")
def q_tox_inputs(spark, d):
    return wl.toxic_inputs(spark, d).groupBy("hit").agg(F.count("*").alias("inputs"))


FREE = 2000  # free samples of each model


@query()
def q_noncanon_free(spark, d):
    """Share of free samples whose tokens are not the tokenizer's own encoding of their text, by model order."""
    out = None
    for order in (3, 2):
        model, tok = _toxic_model(spark, d, order)
        shared = spark.sparkContext.broadcast((model, tok))

        def run(batches, shared=shared):
            for pdf in batches:
                yield pd.DataFrame({"is_canonical": [shared.value[1].is_canonical(p) for p in wl.free_paths(shared.value[0], 32, pdf["id"]) if p]}, dtype=bool)

        cell = ms.noncanonical_rate(spark.range(FREE).mapInPandas(run, "is_canonical boolean")).select(F.lit(order).alias("model_order"), "n", "rate")
        out = cell if out is None else out.unionByName(cell)
    return out


@query()
def q_tox_base(spark, d):
    """Prompted, canonical, no edits: matches of each input."""
    return toxic_run(spark, d)[0].select("query_id", "body_text", F.round("logp", 6).alias("logp"))


@query()
def q_tox_success(spark, d):
    """Success by setting, prompted."""
    model, tok = _toxic_model(spark, d, 3)
    inputs = cut(wl.toxic_inputs(spark, d), "toxic-asked")
    settings = {"canonical": ("prompted", "canonical", 0), "all + edits": ("prompted", "all", 1)}
    found = successes(spark, inputs, lambda row: [wl.toxic_query(row, *s) for s in settings.values()], [model], tok)
    cells = spark.createDataFrame(list(enumerate(settings)), "at int, name string")
    return success_cells(found, inputs, cells.select(F.col("at").alias("setting"), F.lit(0).alias("model"), "name")).select("queries", "successes", "success", F.col("name").alias("setting"))


def success_cells(found, inputs, cells):
    """measures.success_rate in each cell (setting, model, ...) of a table: queries, those with a match, and their share."""
    hits = found.groupBy("setting", "model").agg(F.count("*").alias("hits"))
    asked = inputs.agg(F.count("*").alias("queries"))
    met = cells.join(F.broadcast(hits), ["setting", "model"], "left").join(F.broadcast(asked), F.lit(True))
    return met.withColumn("successes", F.coalesce("hits", F.lit(0))).withColumn("success", F.round(F.col("successes") / F.nullif(F.col("queries"), F.lit(0)), 6))


@query()
def q_tox_volume(spark, d):
    """Unprompted volume by input, all encodings and one edit, capped."""
    return ms.volume(toxic_run(spark, d, "unprompted", "all", 1, limit=CAP)[0], CAP)


@query()
def q_tox_cube(spark, d):
    """Unprompted matches by edited and canonical, with subtotals."""
    return ms.edit_encoding_cube(toxic_run(spark, d, "unprompted", "all", 1, limit=CAP)[0])


@query()
def q_tox_ampl(spark, d):
    """All matches against those without edits and canonical: counted to the end, not up to the cap of the volume."""
    model, tok = _toxic_model(spark, d, 3)
    m = counted(spark, wl.toxic_inputs(spark, d), lambda row: wl.toxic_query(row, "unprompted", "all", 1), model, tok)
    n, plain = (F.coalesce(F.sum(c), F.lit(0)) for c in ("n", "plain"))
    return m.agg(n.alias("n"), plain.alias("plain"), F.round(n / F.nullif(plain, F.lit(0)), 6).alias("gain"))


@query()
def q_tox_edits(spark, d):
    """The edits of unprompted matches against their inputs: positions (in tenths of the sentence) and the characters most often added and removed."""
    m, inputs = toxic_run(spark, d, "unprompted", "all", 1, limit=CAP)
    met = m.where("n_edits > 0").join(inputs.select("query_id", "sentence"), "query_id").select(F.col("sentence").alias("w"), F.col("text").alias("t"))
    met = cut(met, "edited-matches")
    by_char = ms.edit_chars(met, "w", "t").select("op", F.col("c").alias("value"), "n")
    tenth = F.floor(10 * (ms.first_difference("w", "t") - 1) / F.greatest(F.length("w"), F.lit(1))).cast("string")
    at = met.groupBy(F.lit("position").alias("op"), tenth.alias("value")).agg(F.count("*").alias("n"))
    return by_char.unionByName(at)


@query()
def q_tox_fp(spark, d):
    """Edited matches that lost the insult."""
    return ms.edit_false_positives(toxic_run(spark, d, "unprompted", "all", 1, limit=CAP)[0], INSULTS)


@query()
def q_tox_grid(spark, d):
    """Success by mode, encoding, edits and model order: each input is read once for all cells."""
    orders, inputs = (3, 2), cut(wl.toxic_inputs(spark, d), "toxic-asked")
    fitted = [_toxic_model(spark, d, order) for order in orders]
    settings = [(mode, encoding, n_edits) for mode in ("prompted", "unprompted") for n_edits in (0, 1) for encoding in ("canonical", "all")]
    found = successes(spark, inputs, lambda row: [wl.toxic_query(row, *s) for s in settings], [m for m, _ in fitted], fitted[0][1])
    rows = [(i, j, *s, order) for i, s in enumerate(settings) for j, order in enumerate(orders)]
    cells = spark.createDataFrame(rows, "setting int, model int, mode string, encoding string, edits int, model_order int")
    return success_cells(found, inputs, cells).select("mode", "encoding", "edits", "model_order", "queries", "successes", "success")


# -- last words -------------------------------------------------------------------------------------------------------------------------

ITEMS = r"""sents AS (SELECT doc_id, unnest(l) AS s, unnest(range(len(l))) AS sent_no FROM (SELECT doc_id, regexp_extract_all(text, '[^.!?\n|]+[.!?]?"?') AS l FROM documents WHERE lang = 'en')),
toks AS (SELECT doc_id, sent_no, regexp_extract_all(lower(s), '[a-z]+') AS ws, list_append(regexp_extract_all(lower(s), '[a-z]+|[.!?"]'), '</s>') AS w FROM sents),
it0 AS (SELECT item_id, NULL AS doc_id, ws FROM (SELECT item_id, regexp_extract_all(lower(text), '[a-z]+') AS ws FROM benchmark) WHERE len(ws) >= 3
  UNION ALL SELECT 1000000000000 + doc_id * 1000000 + sent_no, doc_id, ws FROM toks WHERE len(ws) >= 5),
items AS (SELECT item_id, doc_id, ws[1 : len(ws) - 1] AS context, ws[len(ws) - 2] AS c2, ws[len(ws) - 1] AS c1, ws[len(ws)] AS answer FROM it0 ORDER BY item_id LIMIT 500),
seq AS (SELECT w FROM toks WHERE len(ws) > 0 AND doc_id NOT IN (SELECT doc_id FROM items WHERE doc_id IS NOT NULL))"""


def cloze_sql(variant: str, order: int) -> str:
    """Every word among the 1000 likeliest tokens, with every way to close it: nothing is left out early, unlike the query."""
    base = f"WITH {ITEMS}, {UNI}, {BI}, {TRI}, {PROBS3}, vocab AS (SELECT DISTINCT w FROM uni), topw AS (SELECT w FROM uni ORDER BY n DESC, w LIMIT 1000), "
    pool = "pool AS (SELECT DISTINCT item_id, c2, c1, w FROM (SELECT item_id, c2, c1, bi.w FROM items JOIN bi USING (c1) UNION ALL SELECT item_id, c2, c1, w FROM items, topw))"
    ranked = f"rk AS (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY round(p, 12) DESC, w) AS rnk FROM ({p_sql('pool', order)}))"
    keep = "rnk <= 1000 AND regexp_full_match(w, '[a-z]+')"
    if variant == "words":
        keep += " AND list_contains((SELECT context FROM items i WHERE i.item_id = rk.item_id), w)"
    if variant == "no_stop":
        keep += f" AND w NOT IN ({listed(wm.STOP)})"
    scored = f"sc AS (SELECT item_id, c1, w, ln(p) AS lp FROM rk WHERE {keep})"
    if variant in ("terminated", "no_stop"):
        ask = lambda name, rows, c2, c1, cand, tokens, lp: f"{name}q AS (SELECT item_id, {cand} AS cand, {c2} AS c2, {c1} AS c1, t AS w, {lp} AS lp0 FROM {rows}, (VALUES {tokens}) AS v(t)), {name} AS (SELECT item_id, cand, c2, c1, w, lp0 + ln(p) AS lp FROM ({p_sql(name + 'q', order)}))"
        one = ask("one", "sc", "c1", "w", "w", "('</s>'), ('.'), ('!'), ('?'), ('\"')", "lp")
        two = ask("two", "(SELECT * FROM one WHERE w IN ('.', '!', '?'))", "c1", "w", "cand", "('</s>'), ('\"')", "lp")
        three = ask("three", "(SELECT * FROM one WHERE w = '\"' UNION ALL SELECT * FROM two WHERE w = '\"')", "c1", "w", "cand", "('</s>')", "lp")
        scored += f", {one}, {two}, {three}, fin AS (SELECT item_id, cand AS w, max(lp) AS lp FROM (SELECT * FROM one UNION ALL SELECT * FROM two UNION ALL SELECT * FROM three) WHERE w = '</s>' GROUP BY ALL)"
    final = "fin" if variant in ("terminated", "no_stop") else "sc"
    return f"{base}{pool}, {ranked}, {scored}, best AS (SELECT item_id, w FROM {final} QUALIFY row_number() OVER (PARTITION BY item_id ORDER BY round(lp, 9) DESC, w) = 1), ans AS (SELECT item_id, answer, best.w AS pred FROM items LEFT JOIN best USING (item_id)) "


@query(f"WITH {ITEMS} SELECT item_id, len(context) AS n_context, answer FROM items")
def q_cloze_items(spark, d):
    return wl.cloze_items(spark, d).select("item_id", F.size("context").cast("long").alias("n_context"), "answer")


@query(cloze_sql("baseline", 3) + "SELECT * FROM ans")
def q_cloze_baseline(spark, d):
    return wl.cloze(spark, d, "baseline")


@query(cloze_sql("words", 3) + "SELECT * FROM ans")
def q_cloze_words(spark, d):
    return wl.cloze(spark, d, "words")


@query(cloze_sql("terminated", 3) + "SELECT * FROM ans")
def q_cloze_terminated(spark, d):
    return wl.cloze(spark, d, "terminated")


@query(cloze_sql("no_stop", 3) + "SELECT * FROM ans")
def q_cloze_nostop(spark, d):
    return wl.cloze(spark, d, "no_stop")


@query(cloze_sql("baseline", 2) + "SELECT count(*) AS items, count(*) FILTER (WHERE pred = answer) AS correct, round(avg(CASE WHEN pred = answer THEN 1.0 ELSE 0.0 END), 6) AS accuracy FROM ans")
def q_cloze_small(spark, d):
    """The smaller model."""
    return ms.accuracy(wl.cloze(spark, d, "baseline", 2))


@query()
def q_cloze_acc(spark, d):
    """Accuracy by variant and model order; items and counts are read once."""
    out, asked = None, wl.Cloze(spark, d)
    for variant in wm.VARIANTS:
        for order in (3, 2):
            a = ms.accuracy(asked.predict(variant, order)).select(F.lit(variant).alias("variant"), F.lit(order).alias("model_order"), "items", "correct", "accuracy")
            out = a if out is None else out.unionByName(a)
    return out


@query(cloze_sql("baseline", 3) + """SELECT round(p5 / t, 6) AS share, round(a5 / t, 6) AS answer_share FROM
(SELECT sum(n) AS p5 FROM (SELECT count(*) AS n FROM ans GROUP BY pred ORDER BY n DESC LIMIT 5)), (SELECT sum(n) AS a5 FROM (SELECT count(*) AS n FROM ans GROUP BY answer ORDER BY n DESC LIMIT 5)), (SELECT count(*) AS t FROM ans)""")
def q_cloze_conc(spark, d):
    """Share of the five commonest predictions, and of the five commonest answers."""
    p = wl.cloze(spark, d, "baseline")
    return ms.concentration(p).join(F.broadcast(ms.concentration(p, "answer").withColumnRenamed("share", "answer_share")), F.lit(True))


# -- dates ------------------------------------------------------------------------------------------------------------------------------

FACTS = """said AS (SELECT o_custkey AS c_custkey, CAST(o_orderdate AS DATE) AS order_date, count(*) AS n FROM orders GROUP BY ALL),
facts AS (SELECT *, row_number() OVER (PARTITION BY c_custkey ORDER BY n DESC, order_date) AS match_rank FROM said)"""
MC = f"""{FACTS}, truth AS (SELECT c_custkey, order_date AS truth FROM facts WHERE match_rank = 1), ch AS (SELECT c_custkey, truth, off, truth + CAST(off AS INT) AS choice FROM truth, (VALUES (0), (31), (97), (211)) AS o(off)),
pr AS (SELECT ch.c_custkey, choice, off = 0 AS is_truth, coalesce(n, 0) + 1 AS w FROM ch LEFT JOIN facts f ON f.c_custkey = ch.c_custkey AND f.order_date = ch.choice),
mc AS (SELECT c_custkey, choice, is_truth, round(w / sum(w) OVER (PARTITION BY c_custkey), 6) AS p FROM pr), mr AS (SELECT *, CAST(row_number() OVER (PARTITION BY c_custkey ORDER BY p DESC, choice) AS INT) AS rnk FROM mc)"""


def facts(spark, d):
    return wl.date_ranks(table(spark, d, "orders"))


@query(f"WITH {FACTS} SELECT c_custkey, order_date, n, match_rank FROM facts WHERE match_rank <= 10")
def q_date_rank(spark, d):
    """The ten likeliest dates of each customer."""
    return facts(spark, d).where("match_rank <= 10")


@query(f"WITH {MC} SELECT * FROM mr")
def q_mc_dates(spark, d):
    return wl.multiple_choice(facts(spark, d))


@query(f"WITH {MC} SELECT chr(64 + k) AS letter, count(*) AS n, count(*) FILTER (WHERE is_truth) AS right_answers FROM (SELECT *, CAST(row_number() OVER (PARTITION BY c_custkey ORDER BY choice) AS INT) AS k FROM mr) WHERE rnk = 1 GROUP BY k")
def q_mc_letters(spark, d):
    """Lettered choices: the letter of the best choice, letters by date."""
    from pyspark.sql import Window

    mc = wl.multiple_choice(facts(spark, d)).withColumn("k", F.row_number().over(Window.partitionBy("c_custkey").orderBy("choice")))
    return mc.where("rnk = 1").groupBy("k").agg(F.count("*").alias("n"), F.count_if("is_truth").alias("right_answers")).select(F.char(F.col("k") + 64).alias("letter"), "n", "right_answers")


@query()
def q_mc_model(spark, d):
    """Closed choices under a model of the said facts: accuracy by the number of choices, by probability and by its mean over tokens."""
    said = verbalised_orders(table(spark, d, "orders"), table(spark, d, "customer"))
    out, scored = None, cut(wl.score_by_counts(wl.closed_choices(said, 9), said, "sentence", 5), "scored")
    for others in (3, 9):
        ranked = wl.ranked_choices(scored.where(F.col("nth") <= others))
        for by in ("rnk", "mean_rnk"):
            ranked = ranked.withColumn(f"by_{by}", F.when(F.col(by) == 1, F.col("is_truth")))
        cell = ranked.agg(F.countDistinct("query_id").alias("customers"), F.count_if("by_rnk").alias("correct"), F.count_if("by_mean_rnk").alias("correct_per_token"))
        cell = cell.select(F.lit(others + 1).alias("choices"), "*", F.round(F.col("correct") / F.col("customers"), 6).alias("accuracy"))
        out = cell if out is None else out.unionByName(cell)
    return out


@query()
def q_mc_model_letters(spark, d):
    """Lettered choices in the prompt, the answer a letter: fitted on all facts and the answered sheets of even customers, asked of odd ones."""
    said = verbalised_orders(table(spark, d, "orders"), table(spark, d, "customer"))
    sheets = cut(wl.answer_sheets(wl.closed_choices(said, 3)), "sheets")
    answered = sheets.where("query_id % 2 = 0").select(F.concat("prompt", "answer").alias("sentence"))
    odd = sheets.where("query_id % 2 = 1")
    asked = odd.select("query_id", "prompt", "answer", F.explode(F.array(*(F.lit(f" {x}") for x in "ABCD"))).alias("choice"))
    best = wl.ranked_choices(wl.score_by_counts(asked, said.select("sentence").unionByName(answered), "sentence", 5)).where("rnk = 1")
    return best.groupBy(F.btrim("choice").alias("letter")).agg(F.count("*").alias("chosen"), F.count_if(F.col("choice") == F.col("answer")).alias("correct"))


DATE = "(January|February|March|April|May|June|July|August|September|October|November|December) [0-9]{1,2}, [0-9]{4}"


@query()
def q_date_query(spark, d):
    """The knowledge probe as a pattern: the ten likeliest dates after each customer's prefix, under a model of the said facts, and the rank of a true one."""
    said = verbalised_orders(table(spark, d, "orders"), table(spark, d, "customer"))
    fitted = wl.chunk_model(said, "sentence", 5)

    def build(row):
        return PatternQuery(" " + DATE, f"Customer {row['query_id']} ordered on", "all", max_tokens=8)

    asked = said.select(F.col("c_custkey").alias("query_id")).distinct()
    found = run_many(spark, asked, build, *fitted, 10).select(F.col("query_id").alias("c_custkey"), "match_rank", "text", "logp")
    truth = said.select("c_custkey", F.col("sentence").alias("text")).distinct().withColumn("known", F.lit(True))
    ranked = cut(found.join(truth, ["c_custkey", "text"], "left"), "date-query")
    best = ranked.where("known").groupBy("c_custkey").agg(F.min("match_rank").alias("truth_rank"))
    return asked.select(F.col("query_id").alias("c_custkey")).join(best, "c_custkey", "left").groupBy("truth_rank").agg(F.count("*").alias("customers"))


MAIL = r"[a-z]+[.][0-9]+@mail[0-9][.]example[.](com|org|net)"


@query()
def q_mail_model(spark, d):
    """Mail addresses drawn out of a character model of the words around them, best first, against those in the documents."""
    docs = table(spark, d, "documents")
    words = docs.select(F.explode(F.regexp_extract_all("text", F.lit(r"[^ \n|]*@[^ \n|]*"), 0)).alias("s"))
    model, tok = wl.character_model(words, "s", 12)
    truth = docs.select(F.explode(F.regexp_extract_all("text", F.lit(MAIL), 0)).alias("text")).distinct()
    found = run_query(PatternQuery(MAIL, encoding="all", rules=wl.TOP_40, max_tokens=48), model, tok, 200)
    return ms.valid_unique(spark.createDataFrame(found, MATCHES).select("text"), truth, "text")


DRAWS = 10  # free responses of each customer


@query()
def q_free_dates(spark, d):
    """Free response: random completions of a fact's prefix, graded by a date pattern and by the truth."""
    said = verbalised_orders(table(spark, d, "orders"), table(spark, d, "customer"))
    model, tok = wl.chunk_model(said, "sentence", 5)
    shared = spark.sparkContext.broadcast((model, tok))
    asked = said.select("c_custkey").distinct()

    def run(batches):
        for pdf in batches:
            rows = [(k, text) for k in pdf["c_custkey"] for _, text, _ in wl.free_texts(*shared.value, f"Customer {k} ordered on", 4, range(k * DRAWS, (k + 1) * DRAWS), wl.Rules())]
            yield pd.DataFrame(rows, columns=["c_custkey", "text"])

    free = asked.repartition(tasks(spark), "c_custkey").mapInPandas(run, "c_custkey long, text string")
    date = F.regexp_extract("text", r"ordered on ([A-Z][a-z]+ [0-9]{1,2}, [0-9]{4})$", 1)
    truth = said.select("c_custkey", F.col("sentence").alias("text")).distinct().withColumn("known", F.lit(1))
    met = free.join(truth, ["c_custkey", "text"], "left")
    return met.agg(F.countDistinct("c_custkey").alias("customers"), F.count("*").alias("samples"), F.count_if(date != "").alias("dates"), F.count_if(F.col("known") == 1).alias("true_dates"))


@query("SELECT c_custkey, CAST(max(o_orderdate) AS DATE) AS last_date FROM customer JOIN orders ON o_custkey = c_custkey WHERE o_orderdate < TIMESTAMP '1997-01-01' GROUP BY c_custkey")
def q_asof_date(spark, d):
    """The last order before a cut-off."""
    o = table(spark, d, "orders").where("o_orderdate < TIMESTAMP_NTZ '1997-01-01 00:00:00'")
    met = o.select(F.col("o_custkey").alias("c_custkey"), "o_orderdate").join(table(spark, d, "customer").select("c_custkey"), "c_custkey")
    return met.groupBy("c_custkey").agg(F.to_date(F.max("o_orderdate")).alias("last_date"))

