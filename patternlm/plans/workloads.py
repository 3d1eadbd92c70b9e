"""The experiments on the given tables: memorised addresses, co-occurrence bias, toxic extraction, last words, dates."""

from __future__ import annotations

from collections.abc import Iterable, Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from patternlm.functions.regex import escape
from patternlm.functions.tokenizer import BOS, EOS, PublicTokenizer, Tokenizer
from patternlm.operators import wordmodel as wm
from patternlm.operators.model import MOST_PACKED, CountModel, ModelTooLarge, NextTokenModel, count_model
from patternlm.operators.traverse import MATCHES, run_query, uniform
from patternlm.plans.query import PatternQuery, Rules, edits
from patternlm.session import cut
from patternlm.sources.io import INSULTS, sentences, table, with_hits

# -- memorised addresses --------------------------------------------------------------------------------------------------------------

URL_PREFIX = "http"
URL_BODY = r"s?://([a-z]+\.)?[a-z]+\.example\.(com|org|net)/[a-z]{2}/[0-9]+(/|[.]html|#top|[?][a-z_]+=[a-z0-9]+(&[a-z_]+=[a-z0-9]+)?)?"
TOP_40 = Rules(top_k=40)


def code_points(df: DataFrame, col: str) -> DataFrame:
    """df with `tokens`: one token a character, its code point."""
    return df.withColumn("tokens", F.transform(F.filter(F.split(col, ""), lambda c: c != ""), lambda c: F.ascii(c)))


def character_model(df: DataFrame, col: str, order: int) -> tuple[CountModel, Tokenizer]:
    """A count model of the characters of df[col] and its tokenizer."""
    rows = code_points(df.select(col), col)
    alphabet = [r[0] for r in rows.select(F.explode("tokens").alias("t")).distinct().collect()]  # at most the characters in use
    tokenizer = Tokenizer([], vocab={chr(t): t for t in sorted(alphabet)})
    return count_model(rows, "tokens", order, len(alphabet)), tokenizer


def chunk_model(df: DataFrame, col: str, order: int) -> tuple[CountModel, Tokenizer]:
    """A count model whose tokens are whole words, each with the space before it; the number of words is checked."""
    words = cut(df.select(F.regexp_extract_all(col, F.lit(" ?[^ ]+"), 0).alias("w")).withColumn("row", F.monotonically_increasing_id()), "chunks")  # a table: ids stay
    known = words.select(F.explode("w").alias("w")).distinct().orderBy("w").limit(MOST_PACKED + 1).collect()
    if len(known) > MOST_PACKED:
        raise ModelTooLarge(f"more than {MOST_PACKED} words")
    vocab = {r[0]: i for i, r in enumerate(known)}
    tokenizer = Tokenizer([], vocab=vocab)
    tokenizer.pieces = _whole
    ids = df.sparkSession.createDataFrame(list(vocab.items()), "w string, tok int")
    placed = words.select("row", F.posexplode("w").alias("pos", "w")).join(ids, "w")
    rows = placed.groupBy("row").agg(F.transform(F.sort_array(F.collect_list(F.struct("pos", "tok"))), lambda s: s["tok"]).alias("tokens"))
    return count_model(rows, "tokens", order, len(vocab)), tokenizer


def _whole(chunk: str) -> list[str]:
    return [chunk]


def url_model(spark: SparkSession, d: str, order: int = 24) -> tuple[CountModel, Tokenizer]:
    return character_model(table(spark, d, "pages").where("page_id % 5 <> 0"), "url", order)


def extract_urls(spark: SparkSession, d: str, limit: int, order: int = 24, rules: Rules = TOP_40, **changes) -> DataFrame:
    """The likeliest addresses of the pattern, best first."""
    model, tokenizer = url_model(spark, d, order)
    query = PatternQuery(URL_BODY, URL_PREFIX, encoding="all", rules=rules, require_eos=True, **changes)
    return spark.createDataFrame(run_query(query, model, tokenizer, limit), MATCHES)


def free_paths(model: NextTokenModel, n_tokens: int, ids: Iterable[int], seed: int = 42) -> list[tuple[int, ...]]:
    """Token paths drawn freely from the start of a sequence, without rules, up to the end token."""
    out = []
    for i in ids:
        path: tuple[int, ...] = ()
        for step in range(n_tokens):
            tokens, p, _, _, order = model.distribution((BOS, *path))
            u = uniform(seed, int(i), step) * float(p.sum())
            j = int(order[min(int((p[order].cumsum() <= u).sum()), len(order) - 1)])
            if tokens[j] == EOS:
                break
            path = (*path, int(tokens[j]))
        out.append(path)
    return out


def _drawn(model: NextTokenModel, ctx: tuple[int, ...], u: float, top_k: int | None) -> int:
    """The token at u in [0, 1) of the distribution's order. A count model without a rule makes no distribution over its vocabulary."""
    if isinstance(model, CountModel) and not top_k:
        model.lookups += 1
        u *= model.known_mass(ctx)
        for token, q in model.likeliest(ctx):
            u -= q
            if u < 0:
                break
        return token
    tokens, p, _, _, order = model.distribution(ctx)
    keep = order[:top_k] if top_k else order
    u *= float(p[keep].sum())
    for j in keep:
        u -= p[j]
        if u < 0:
            break
    return int(tokens[j])


def free_cuts(model: NextTokenModel, tokenizer: Tokenizer, prefix: str, lengths: Sequence[int], ids: Iterable[int], rules: Rules = TOP_40, seed: int = 42) -> list[tuple[int, int, str, bool]]:
    """Samples (stop length, id, text, ended): tokens at random after the prefix, up to the end token; a draw goes to the longest stop length and is cut at the others."""
    out = []
    for i in ids:
        start, ended = tokenizer.encode(prefix), False
        path = start
        for step in range(max(lengths)):
            token = _drawn(model, (BOS, *path), uniform(seed, int(i), step), rules.top_k)
            if token == EOS:
                ended = True
                break
            path = (*path, token)
        drawn = len(path) - len(start)
        out += [(n, int(i), tokenizer.decode(path[: len(start) + n]), ended and drawn < n) for n in lengths]
    return out


def free_texts(model: NextTokenModel, tokenizer: Tokenizer, prefix: str, n_tokens: int, ids: Iterable[int], rules: Rules = TOP_40, seed: int = 42) -> list[tuple[int, str, bool]]:
    """Samples (id, text, ended): n_tokens tokens at random after the prefix, or up to the end token."""
    return [x[1:] for x in free_cuts(model, tokenizer, prefix, (n_tokens,), ids, rules, seed)]


def free_samples(spark: SparkSession, model: NextTokenModel, tokenizer: Tokenizer, prefix: str, lengths: Sequence[int], n_samples: int, rules: Rules = TOP_40, seed: int = 42) -> DataFrame:
    """The baseline: (stop_length, sample_id, text, ended) of n_samples free samples at each stop length, the same on every rerun and partitioning; the model goes to a task once."""
    shared = spark.sparkContext.broadcast((model, tokenizer))

    def run(batches):
        for pdf in batches:
            yield pd.DataFrame(free_cuts(*shared.value, prefix, lengths, pdf["id"], rules, seed), columns=["stop_length", "sample_id", "text", "ended"])

    return spark.range(n_samples).mapInPandas(run, "stop_length int, sample_id long, text string, ended boolean")


def free_sample(spark: SparkSession, model: NextTokenModel, tokenizer: Tokenizer, prefix: str, n_tokens: int, n_samples: int, rules: Rules = TOP_40, seed: int = 42) -> DataFrame:
    """The same at one stop length: (sample_id, text, ended)."""
    return free_samples(spark, model, tokenizer, prefix, (n_tokens,), n_samples, rules, seed).drop("stop_length")


def graded(samples: DataFrame, truth: DataFrame, pattern: str, keep: tuple[str, ...] = ()) -> DataFrame:
    """Samples with the address-like start of their text and whether it is known, and their columns `keep`."""
    cut = samples.withColumn("found", F.regexp_extract("text", f"^({pattern})", 1)).withColumn("attempt", F.col("sample_id"))
    known = truth.select(F.col("url").alias("__u")).distinct()
    met = cut.join(known, F.col("found") == F.col("__u"), "left")
    return met.select(*keep, "attempt", F.when(F.col("found") != "", F.col("found")).otherwise(F.col("text")).alias("text"), "ended", (F.col("found") != "").alias("in_pattern"), F.col("__u").isNotNull().alias("in_truth"))


# -- co-occurrence bias ---------------------------------------------------------------------------------------------------------------

GROUPS = ("this", "that")
OUTCOMES = ("the", "of", "and", "to", "in", "was", "is", "for", "with", "by")


def slot_pairs(docs: DataFrame) -> DataFrame:
    """Counts of (group, outcome) side by side in English text."""
    words = docs.where("lang = 'en'").select(F.expr("regexp_extract_all(lower(text), '[a-z]+', 0)").alias("w")).where(F.size("w") >= 2)
    pairs = F.transform(F.sequence(F.lit(0), F.size("w") - 2), lambda i: F.struct(F.get("w", i).alias("x"), F.get("w", i + 1).alias("y")))
    hit = words.select(F.explode(F.filter(pairs, lambda p: p["x"].isin(*GROUPS) & p["y"].isin(*OUTCOMES))).alias("p")).select("p.*")
    return hit.groupBy("x", "y").agg(F.count("*").alias("n"))


def bias_query(encoding: str = "canonical", prefix: bool = True, n_edits: int = 0, groups: tuple[str, ...] = GROUPS) -> PatternQuery:
    """The template of groups and outcomes: with the group as prefix, or in the body."""
    head, tail = f"({'|'.join(groups)}) ", f"({'|'.join(OUTCOMES)})"
    q = PatternQuery(tail, head, encoding) if prefix else PatternQuery(head + tail, "", encoding)
    return q.but(preprocessors=(edits(n_edits, "abcdefghijklmnopqrstuvwxyz", "both"),)) if n_edits else q


# -- toxic extraction -----------------------------------------------------------------------------------------------------------------


def toxic_inputs(spark: SparkSession, d: str, words: tuple[str, ...] = INSULTS, most: int | None = None) -> DataFrame:
    """(query_id, sentence, hit, prompt): distinct sentences with a listed word; most keeps the shortest so many."""
    hits = with_hits(sentences(table(spark, d, "documents").where("lang = 'en'")), "sentence", words).select("sentence", "hit", "prompt").distinct()
    # numbered in two steps, so that no task orders all of them: lengths first, then sentences inside a length
    sized = cut(hits.withColumn("size", F.length("sentence")), "toxic-inputs")
    per = sized.groupBy("size").agg(F.count("*").alias("n"))
    base = per.select("size", F.coalesce(F.sum("n").over(Window.orderBy("size").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    inside = F.row_number().over(Window.partitionBy("size").orderBy("sentence"))
    ranked = sized.withColumn("nth", inside).join(F.broadcast(base), "size").withColumn("query_id", (F.col("base") + F.col("nth")).cast("long")).select("sentence", "hit", "prompt", "query_id")
    return ranked.where(F.col("query_id") <= most) if most else ranked


def toxic_query(row: dict, mode: str = "prompted", encoding: str = "canonical", n_edits: int = 0, words: Iterable[str] = INSULTS) -> PatternQuery:
    body, prefix = ("|".join(words), escape(row["prompt"])) if mode == "prompted" else (escape(row["sentence"]), "")
    pre = (edits(n_edits, "abcdefghijklmnopqrstuvwxyz "),) if n_edits else ()
    return PatternQuery(body, prefix, encoding, TOP_40, preprocessors=pre, max_tokens=200)


def token_model(spark: SparkSession, texts: DataFrame, col: str, tokenizer: Tokenizer, order: int) -> CountModel:
    """A count model over a tokenizer's ids."""
    shared = spark.sparkContext.broadcast(tokenizer)

    def run(batches):
        t = shared.value
        for pdf in batches:
            yield pd.DataFrame({"tokens": [list(t.encode(x)) for x in pdf[col]]})

    return count_model(texts.select(col).mapInPandas(run, "tokens array<int>"), "tokens", order, len(tokenizer.vocab))


# -- last words -----------------------------------------------------------------------------------------------------------------------


def cloze_items(spark: SparkSession, d: str, most: int = 500) -> DataFrame:
    """(item_id, doc_id, context, c2, c1, answer): the last word of benchmark passages and then of English sentences, in order, `most` in all.

    Sentences of documents (five words or more) have ids from 10**12 on; doc_id is null for passages.
    """
    passages = table(spark, d, "benchmark").select("item_id", F.lit(None).cast("long").alias("doc_id"), F.expr("regexp_extract_all(lower(text), '[a-z]+', 0)").alias("ws"))
    said = wm.marked_sequences(table(spark, d, "documents")).where(F.size("ws") >= 5)
    said = said.select((F.lit(10**12) + F.col("doc_id") * 10**6 + F.col("sent_no")).alias("item_id"), "doc_id", "ws")
    w = passages.where(F.size("ws") >= 3).unionByName(said).orderBy("item_id").limit(most)
    at = lambda k: F.get("ws", F.size("ws") - k)
    return w.select("item_id", "doc_id", F.slice("ws", 1, F.size("ws") - 1).alias("context"), at(3).alias("c2"), at(2).alias("c1"), at(1).alias("answer"))


class Cloze:
    """Items and the counts of all other English documents, read once for all variants and orders."""

    def __init__(self, spark: SparkSession, d: str, most: int = 500):
        self.items = cut(cloze_items(spark, d, most), "cloze-items")
        given = self.items.where("doc_id IS NOT NULL").select("doc_id").distinct()  # at most `most` rows
        self.counts = wm.counts(wm.marked_sequences(table(spark, d, "documents").join(F.broadcast(given), "doc_id", "left_anti")))
        self.known: dict[int, tuple] = {}

    def predict(self, variant: str = "baseline", order: int = 3) -> DataFrame:
        """(item_id, answer, pred) of one of wordmodel.VARIANTS."""
        if order not in self.known:
            model = wm.fit(None, order, self.counts)
            self.known[order] = model, wm.ranked_candidates(model, self.items)
        model, found = self.known[order]
        return wm.predict(model, self.items, variant, found=found)


def cloze(spark: SparkSession, d: str, variant: str = "baseline", order: int = 3) -> DataFrame:
    return Cloze(spark, d).predict(variant, order)


# -- dates ----------------------------------------------------------------------------------------------------------------------------


def date_ranks(orders: DataFrame) -> DataFrame:
    """Every date of every customer, ranked by how often it was said (ties by date): the model of facts is their counts."""
    said = orders.select(F.col("o_custkey").alias("c_custkey"), F.to_date("o_orderdate").alias("order_date")).groupBy("c_custkey", "order_date").agg(F.count("*").alias("n"))
    return said.withColumn("match_rank", F.row_number().over(Window.partitionBy("c_custkey").orderBy(F.desc("n"), "order_date")).cast("long"))


def multiple_choice(facts: DataFrame, offsets: tuple[int, ...] = (0, 31, 97, 211)) -> DataFrame:
    """The true date against three others: (c_custkey, choice, p, rnk), p by smoothed counts."""
    truth = facts.where("match_rank = 1").select("c_custkey", F.col("order_date").alias("truth"))
    choices = truth.select("c_custkey", "truth", F.explode(F.array(*map(F.lit, offsets))).alias("off")).withColumn("choice", F.expr("date_add(truth, off)"))
    met = choices.join(facts.select("c_custkey", F.col("order_date").alias("choice"), "n"), ["c_custkey", "choice"], "left")
    met = met.withColumn("p", F.coalesce("n", F.lit(0)) + 1)
    by = Window.partitionBy("c_custkey")
    met = met.withColumn("p", F.round(F.col("p") / F.sum("p").over(by), 6))
    return met.withColumn("rnk", F.row_number().over(by.orderBy(F.desc("p"), "choice"))).select("c_custkey", "choice", (F.col("off") == 0).alias("is_truth"), "p", "rnk")


def score_choices(asked: DataFrame, model: NextTokenModel, tokenizer: Tokenizer) -> DataFrame:
    """asked (query_id, prompt, choice) -> (query_id, choice, logp, n_tokens, rnk, mean_rnk): closed choices by their probability after the prompt, and by its mean over tokens; ties by choice."""
    shared = asked.sparkSession.sparkContext.broadcast((model, tokenizer))

    def run(batches):
        m, t = shared.value
        for pdf in batches:
            tokens, logp = [t.encode(c) for c in pdf["choice"]], []
            for prompt, choice in zip(pdf["prompt"], tokens, strict=True):
                path = (BOS, *t.encode(prompt), *choice)
                logp.append(sum(m.ruled(path[:i], [path[i]], Rules())[0] for i in range(len(path) - len(choice), len(path))))
            yield pd.DataFrame({"query_id": pdf["query_id"], "choice": pdf["choice"], "logp": logp, "n_tokens": [len(x) for x in tokens]})

    return ranked_choices(asked.select("query_id", "prompt", "choice").mapInPandas(run, "query_id long, choice string, logp double, n_tokens int"))


def ranked_choices(scored: DataFrame) -> DataFrame:
    """scored with the ranks `rnk` and `mean_rnk` of each query's choices."""
    rank = lambda by: F.row_number().over(Window.partitionBy("query_id").orderBy(by.desc(), "choice"))
    return scored.select("*", rank(F.col("logp")).alias("rnk"), rank(F.col("logp") / F.col("n_tokens")).alias("mean_rnk"))


def marked_chunks(col: str) -> Column:
    """The words of a text as chunk_model takes them, without a space: + stands for one that had a space before it, - for any other."""
    return F.transform(F.regexp_extract_all(col, F.lit(" ?[^ ]+"), 0), lambda w: F.when(w.startswith(" "), F.concat(F.lit("+"), F.substring(w, 2, 2**31 - 1))).otherwise(F.concat(F.lit("-"), w)))


def last_words(ctx: Column, k: int) -> Column:
    """The last k words of a context, all of them if it has fewer."""
    return F.substring_index(ctx, " ", -k) if k else F.lit("")


def chunk_counts(df: DataFrame, col: str, order: int) -> list[DataFrame]:
    """For k = 0..order-1 the counts (ctx, tok, cnt) after contexts of k words, joined by spaces; ^ opens a sequence and $ ends it."""
    t = df.select(F.concat(F.array(F.lit("^")), marked_chunks(col), F.array(F.lit("$"))).alias("t"))
    at = t.select("t", F.explode(F.sequence(F.lit(2), F.size("t"))).alias("i")).withColumn("k", F.least(F.lit(order - 1), F.col("i") - 1))
    words = F.array_join(F.slice("t", F.col("i") - F.col("k"), F.col("k")), " ")
    longest = cut(at.select(words.alias("ctx"), F.element_at("t", F.col("i")).alias("tok"), "k").groupBy("ctx", "tok", "k").agg(F.count("*").alias("cnt")), "chunk-counts")
    out = [longest.where(F.col("k") == order - 1).select("ctx", "tok", "cnt")]
    for k in range(order - 2, -1, -1):
        shorter = out[-1].select(last_words(F.col("ctx"), k).alias("ctx"), "tok", "cnt").unionByName(longest.where(F.col("k") == k).select("ctx", "tok", "cnt"))
        out.append(cut(shorter.groupBy("ctx", "tok").agg(F.sum("cnt").alias("cnt")), "chunk-counts"))
    return out[::-1]


def score_by_counts(asked: DataFrame, df: DataFrame, col: str, order: int) -> DataFrame:
    """asked (query_id, prompt, choice, ...) -> the same without prompt, with logp and n_tokens: as score_choices under chunk_model(df, col, order), by joins with the counts.

    Neither a vocabulary nor a model is held by the driver or by a task. Each different (context, word) is looked up once at each length of context; the steps
    of the interpolation are those of CountModel. Logarithms are added from the least on, so the order of a choice's words makes no tie unequal.
    """
    counts = chunk_counts(df, col, order)
    keys = [c for c in asked.columns if c != "prompt"]
    t, n = F.concat(F.array(F.lit("^")), marked_chunks("prompt"), F.col("w")), F.size("w")
    at = asked.select("prompt", *keys, marked_chunks("choice").alias("w")).select(*keys, n.cast("int").alias("n_tokens"), t.alias("t"))
    place = F.sequence(F.size("t") - F.col("n_tokens") + 1, F.size("t"))
    at = at.select("*", F.explode_outer(F.when(F.col("n_tokens") > 0, place)).alias("i")).withColumn("k", F.least(F.lit(order - 1), F.col("i") - 1))
    words = F.array_join(F.slice("t", F.col("i") - F.col("k"), F.col("k")), " ")
    places = cut(at.select(*keys, "n_tokens", words.alias("ctx"), F.element_at("t", F.col("i")).alias("tok")), "choice-places")
    wanted = [cut(places.where("tok IS NOT NULL").select("ctx", "tok").distinct(), "wanted")]
    for k in range(order - 2, -1, -1):
        wanted.append(cut(wanted[-1].select(last_words(F.col("ctx"), k).alias("ctx"), "tok").distinct(), "wanted"))
    known = counts[0].where("tok <> '$'").count()  # different words: a number reaches the driver
    p = wanted.pop().withColumn("p", F.lit(1.0 / (known + 1)))
    for k, seen in enumerate(counts):
        if k:
            below = p.select(F.col("ctx").alias("shorter"), "tok", "p")
            p = wanted.pop().withColumn("shorter", last_words(F.col("ctx"), k - 1)).join(below, ["shorter", "tok"]).select("ctx", "tok", "p")
        stats = seen.groupBy("ctx").agg(F.sum("cnt").alias("n"), F.count("*").alias("d"))
        whole = F.col("n") + F.col("d")
        here = F.when(F.col("n").isNull(), F.col("p")).otherwise(F.col("p") * (F.col("d") / whole) + F.coalesce(F.col("cnt") / whole, F.lit(0.0)))
        p = p.join(stats, "ctx", "left").join(seen, ["ctx", "tok"], "left").select("ctx", "tok", here.alias("p"))
    logp = F.aggregate(F.sort_array(F.collect_list("p")), F.lit(0.0), lambda total, x: total + F.ln(x))
    return places.join(p, ["ctx", "tok"], "left").groupBy(*keys, "n_tokens").agg(logp.alias("logp"))


def closed_choices(said: DataFrame, others: int) -> DataFrame:
    """(query_id, prompt, choice, is_truth, nth): each customer's first date among the first dates of `others` customers with the next keys, in a ring; equal dates
    once, under the first place `nth` (the customer's own is 0), so those up to a smaller number of others are the choices of that number."""
    first = said.groupBy("c_custkey").agg(F.min_by("sentence", "order_date").alias("sentence"))
    first = cut(first.select("c_custkey", F.regexp_extract("sentence", "ordered on(.*)$", 1).alias("choice")), "first-dates")
    near = first.select(F.col("c_custkey").alias("query_id"), F.explode(F.sequence(F.lit(0), F.lit(others))).alias("k"))
    near = near.select("query_id", "k", F.pmod(F.col("query_id") + F.col("k"), first.agg(F.max("c_custkey") + 1).scalar()).alias("c_custkey"))
    asked = near.join(first, "c_custkey").groupBy("query_id", "choice").agg(F.min("k").alias("nth"))
    true = said.select(F.col("c_custkey").alias("query_id"), F.regexp_extract("sentence", "ordered on(.*)$", 1).alias("choice")).distinct().withColumn("is_truth", F.lit(True))
    prompt = F.concat(F.lit("Customer "), F.col("query_id").cast("string"), F.lit(" ordered on"))
    return asked.join(true, ["query_id", "choice"], "left").select("query_id", prompt.alias("prompt"), "choice", F.coalesce("is_truth", F.lit(False)).alias("is_truth"), "nth")


def answer_sheets(choices: DataFrame) -> DataFrame:
    """(query_id, prompt, answer): the choices lettered by their text and written into the prompt; the answer is the letter of the first true one."""
    lettered = choices.withColumn("k", F.row_number().over(Window.partitionBy("query_id").orderBy("choice"))).withColumn("letter", F.char(F.col("k") + 64))
    lines = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("k", "letter", "choice"))), lambda x: F.concat(F.lit(" "), x["letter"], F.lit(")"), x["choice"])), "")
    sheets = lettered.groupBy("query_id").agg(F.first("prompt").alias("prompt"), lines.alias("lines"), F.min(F.when(F.col("is_truth"), F.col("letter"))).alias("letter"))
    return sheets.select("query_id", F.concat("prompt", "lines", F.lit(" Answer:")).alias("prompt"), F.concat(F.lit(" "), "letter").alias("answer"))
