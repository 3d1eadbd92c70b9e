"""Scans, text preparation and extraction truth."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from patternlm.queries import query
from patternlm.sources.io import INSULTS, MORE_INSULTS, english_words, sample_rows, sentences, table, verbalised_orders, with_hits, word_pattern

SIX = word_pattern(INSULTS)
SENTENCES = r"""sent AS (SELECT doc_id, sent_no, trim(s) AS sentence FROM (SELECT doc_id, unnest(p) AS s, unnest(range(0, len(p))) AS sent_no
FROM (SELECT doc_id, regexp_split_to_array(text, '[.!?\n|]') AS p FROM documents)) WHERE trim(s) <> '')"""
PHONE, EMAIL, IPV4 = r"\+1 \([0-9]{3}\) 555-[0-9]{4}", r"[a-z]+\.[0-9]+@mail[0-9]+\.example\.com", r"[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}"
URL = r"https?://[a-z.-]+\.example\.(com|org|net)/[a-z]{2}/[0-9]+"


@query(f"SELECT doc_id, source FROM documents WHERE regexp_matches(text, '{SIX}')")
def q_grep_match(spark, d):
    return table(spark, d, "documents").where(F.col("text").rlike("|".join(INSULTS)) & F.col("text").rlike(SIX)).select("doc_id", "source")


@query(f"SELECT lang, count(*) AS n, count(*) FILTER (WHERE regexp_matches(text, '{word_pattern(MORE_INSULTS)}')) AS hits FROM documents GROUP BY lang")
def q_grep_count(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.count("*").alias("n"), F.count_if(F.col("text").rlike(word_pattern(MORE_INSULTS))).alias("hits"))


@query(f"WITH {SENTENCES} SELECT doc_id, CAST(sent_no AS INT) AS sent_no, sentence FROM sent")
def q_sentences(spark, d):
    return sentences(table(spark, d, "documents"))


@query(f"""WITH {SENTENCES} SELECT doc_id, CAST(sent_no AS INT) AS sent_no, regexp_extract(sentence, '{SIX}', 2) AS hit,
regexp_extract(sentence, '^(.*?)({SIX})', 1) || regexp_extract(sentence, '{SIX}', 1) AS prompt FROM sent WHERE regexp_matches(sentence, '{SIX}')""")
def q_prompts(spark, d):
    return with_hits(sentences(table(spark, d, "documents")), "sentence", INSULTS).select("doc_id", "sent_no", "hit", "prompt")


@query(f"SELECT doc_id, lang, n_chars FROM documents WHERE ('0x' || substr(md5(doc_id || ':42'), 1, 8))::BIGINT < {round(0.1 * 2**32)}")
def q_row_sample(spark, d):
    """A seeded tenth of the rows."""
    return sample_rows(table(spark, d, "documents"), "doc_id", 0.1).select("doc_id", "lang", "n_chars")


@query("SELECT conv_id, turn, count(*) AS n FROM (SELECT conv_id, turn, unnest(regexp_extract_all(text, 'the ([a-z]+) of', 1)) AS slot FROM conversations WHERE role = 'assistant') GROUP BY ALL")
def q_grep_turns(spark, d):
    """How often the assistant's turns match a template: a second corpus to scan."""
    said = table(spark, d, "conversations").where("role = 'assistant'").select("conv_id", "turn", F.size(F.regexp_extract_all("text", F.lit("the ([a-z]+) of"), 1)).cast("long").alias("n"))
    return said.where("n > 0")


@query("SELECT doc_id, lang, n_chars FROM documents ORDER BY doc_id LIMIT 500")
def q_first_500(spark, d):
    return table(spark, d, "documents").select("doc_id", "lang", "n_chars").orderBy("doc_id").limit(500)


@query("SELECT lang, CAST(quantile_cont(n_chars, 0.5) AS DOUBLE) AS p50, CAST(quantile_cont(n_chars, 0.9) AS DOUBLE) AS p90, max(n_chars) AS longest FROM documents GROUP BY lang")
def q_len_percentiles(spark, d):
    return table(spark, d, "documents").groupBy("lang").agg(F.percentile("n_chars", 0.5).alias("p50"), F.percentile("n_chars", 0.9).alias("p90"), F.max("n_chars").alias("longest"))


@query("SELECT md5(text) AS digest, min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY md5(text)")
def q_dedup_exact(spark, d):
    return table(spark, d, "documents").groupBy(F.md5(F.col("text").cast("binary")).alias("digest")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies"))


@query("""SELECT c_custkey, CAST(o_orderdate AS DATE) AS order_date, 'Customer ' || c_custkey || ' ordered on ' || strftime(o_orderdate, '%B %-d, %Y') AS sentence
FROM orders JOIN customer ON o_custkey = c_custkey""")
def q_verbalise(spark, d):
    return verbalised_orders(table(spark, d, "orders"), table(spark, d, "customer"))


@query("""WITH w AS (SELECT item_id, text, string_split(text, ' ') AS w FROM benchmark)
SELECT item_id, min(doc_id) AS doc_id, count(*) AS documents FROM w JOIN documents d ON contains(d.text, w.text) WHERE len(w) >= 8 GROUP BY item_id""")
def q_contamination(spark, d):
    """Passages inside documents: an 8-word key joins, containment of the whole passage verifies."""
    items = table(spark, d, "benchmark").withColumn("w", F.split("text", " ")).where(F.size("w") >= 8)
    # the passage's last word may be cut from a longer one in a document, its first preceded by a part: inner words make the key
    items = items.select("item_id", F.col("text").alias("passage"), F.xxhash64(F.array_join(F.slice("w", 2, 6), " ")).alias("key"))
    docs = table(spark, d, "documents")
    words = docs.select("doc_id", F.split("text", " ").alias("w"))
    runs = F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - 5, F.lit(1))), lambda i: F.xxhash64(F.array_join(F.slice("w", i, 6), " ")))
    # only ids and hashes meet the passages; texts are joined again for the hits
    hits = words.select("doc_id", F.explode(F.array_distinct(runs)).alias("key")).join(items, "key").select("doc_id", "item_id", "passage")
    hit = docs.select("doc_id", "text").join(hits, "doc_id").where(F.contains("text", F.col("passage")))
    return hit.select("item_id", "doc_id").distinct().groupBy("item_id").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("documents"))


@query("SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY ROLLUP (lang, source)")
def q_rollup_lang_source(spark, d):
    return table(spark, d, "documents").rollup("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query(f"SELECT page_id, url, page_id % 5 <> 0 AS train, regexp_extract(url, '^https?://([^/]+)', 1) AS host FROM pages WHERE regexp_matches(url, '^{URL}')")
def q_url_truth(spark, d):
    return table(spark, d, "pages").where(F.col("url").rlike(f"^{URL}")).select("page_id", "url", (F.col("page_id") % 5 != 0).alias("train"), F.parse_url("url", F.lit("HOST")).alias("host"))


def _extract(spark, d, pattern):
    return table(spark, d, "documents").select("doc_id", F.explode(F.regexp_extract_all("text", F.lit(pattern), 0)).alias("found"))


@query(f"SELECT doc_id, unnest(regexp_extract_all(text, '{PHONE}')) AS found FROM documents")
def q_phone_extract(spark, d):
    return _extract(spark, d, PHONE)


@query(f"SELECT doc_id, unnest(regexp_extract_all(text, '{EMAIL}')) AS found FROM documents")
def q_email_extract(spark, d):
    return _extract(spark, d, EMAIL)


@query(f"SELECT doc_id, unnest(regexp_extract_all(text, '{IPV4}')) AS found FROM documents")
def q_ip_extract(spark, d):
    return _extract(spark, d, IPV4)


def _tagged(kind):
    return lambda x: F.struct(F.lit(kind).alias("kind"), x.alias("x"))


@query(f"""WITH f AS (SELECT 'phone' AS kind, unnest(regexp_extract_all(text, '{PHONE}')) AS x FROM documents UNION ALL SELECT 'mail', unnest(regexp_extract_all(text, '{EMAIL}')) FROM documents
UNION ALL SELECT 'ip', unnest(regexp_extract_all(text, '{IPV4}')) FROM documents)
SELECT kind, count(*) AS n, count(DISTINCT x) AS uniq, round(1 - count(DISTINCT x) / count(*), 6) AS dup_rate FROM f GROUP BY kind""")
def q_dup_rate(spark, d):
    from patternlm.operators.measures import duplicate_rate

    kinds = (("phone", PHONE), ("mail", EMAIL), ("ip", IPV4))
    docs = table(spark, d, "documents")
    found = docs.select(F.explode(F.concat(*(F.transform(F.regexp_extract_all("text", F.lit(p), 0), _tagged(k)) for k, p in kinds))).alias("f")).select("f.*")
    return duplicate_rate(found, "x", ["kind"])


@query(f"""WITH a AS (SELECT row_number() OVER (ORDER BY doc_id, i) AS attempt, x FROM (SELECT doc_id, unnest(m) AS x, unnest(range(0, len(m))) AS i
FROM (SELECT doc_id, regexp_extract_all(text, '{IPV4}') AS m FROM documents))),
f AS (SELECT attempt, row_number() OVER (PARTITION BY x ORDER BY attempt) = 1 AS fresh FROM a)
SELECT attempt, CAST(sum(CASE WHEN fresh THEN 1 ELSE 0 END) OVER (ORDER BY attempt) AS BIGINT) AS found FROM f""")
def q_discovery_curve(spark, d):
    from patternlm.operators.measures import discovery_curve

    docs = table(spark, d, "documents").select("doc_id", F.posexplode(F.regexp_extract_all("text", F.lit(IPV4), 0)).alias("i", "x"))
    attempts = docs.withColumn("attempt", F.row_number().over(Window.orderBy("doc_id", "i")))  # a report over the hits only
    return discovery_curve(attempts, "attempt", "x")


INSULT_WORDS = "(" + "|".join(MORE_INSULTS) + ")"


@query(f"""SELECT toxic, count(*) AS n, count(*) FILTER (WHERE regexp_matches(text, '{word_pattern(MORE_INSULTS)}')) AS found FROM labels JOIN documents USING (doc_id) GROUP BY toxic""")
def q_detector_quality(spark, d):
    docs = table(spark, d, "documents").select("doc_id", F.col("text").rlike(word_pattern(MORE_INSULTS)).alias("hit"))
    return table(spark, d, "labels").select("doc_id", "toxic").join(docs, "doc_id").groupBy("toxic").agg(F.count("*").alias("n"), F.count_if("hit").alias("found"))


@query("""WITH w AS (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS w FROM documents WHERE lang = 'en'),
c AS (SELECT w, count(*) AS n FROM w GROUP BY w), p AS (SELECT substring(w, i, 1) || substring(w, i + 1, 1) AS pair, n FROM c, LATERAL (SELECT unnest(range(1, length(w))) AS i))
SELECT pair, CAST(sum(n) AS BIGINT) AS n FROM p GROUP BY pair""")
def q_pair_counts(spark, d):
    """Adjacent letter pairs, weighted by word counts: the statistic that merge lists are made of."""
    counts = english_words(table(spark, d, "documents")).select(F.explode("w").alias("w")).groupBy("w").agg(F.count("*").alias("n"))
    letters = F.filter(F.split("w", ""), lambda c: c != "")
    pairs = counts.select("n", letters.alias("c")).select("n", F.explode(F.zip_with(F.slice("c", 1, F.size("c") - 1), F.slice("c", 2, F.size("c")), lambda a, b: F.concat(a, b))).alias("pair"))
    return pairs.groupBy("pair").agg(F.sum("n").alias("n"))


@query("""WITH w AS (SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS w FROM documents WHERE lang = 'en') SELECT count(*) AS words, true AS estimate_within_10_percent FROM w""")
def q_approx_vocab(spark, d):
    words = english_words(table(spark, d, "documents")).select(F.explode("w").alias("w"))
    return words.agg(F.countDistinct("w").alias("words"), (F.abs(F.approx_count_distinct("w", 0.02) - F.countDistinct("w")) <= 0.1 * F.countDistinct("w")).alias("estimate_within_10_percent"))
