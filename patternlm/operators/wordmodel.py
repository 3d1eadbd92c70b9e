"""A word model as relations: Witten-Bell interpolated unigrams, bigrams and trigrams, joined rather than packed.

Sequences are word arrays; each ends in END. p1(w) = (n(w) + D/(D+1)) / (N + D), p2(w|c) = (n(c,w) + D(c) p1(w)) / (N(c) + D(c)), p3 likewise over p2; a
context never seen hands over to the shorter one.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from patternlm.session import cut
from patternlm.sources.io import sentences

END = "</s>"
# Frequent English function words.
STOP = ("the", "of", "and", "to", "in", "is", "was", "for", "with", "by", "a", "an", "that", "this", "it", "on", "as", "at", "be", "are", "from", "or")


def sentence_words(docs: DataFrame) -> DataFrame:
    """(doc_id, sent_no, w): words of English sentences, closed by END."""
    s = sentences(docs.where("lang = 'en'")).select("doc_id", "sent_no", F.expr("regexp_extract_all(lower(sentence), '[a-z]+', 0)").alias("w"))
    return s.where(F.size("w") > 0).withColumn("w", F.concat("w", F.array(F.lit(END))))


def grams(seq: DataFrame, n: int) -> DataFrame:
    """Counts of runs of n words: columns c2, c1, w as far as n goes."""
    names = ["c2", "c1", "w"][3 - n :]
    runs = F.transform(F.sequence(F.lit(0), F.size("w") - n), lambda i: F.struct(*(F.get("w", i + k).alias(x) for k, x in enumerate(names))))
    long_enough = seq.where(F.size("w") >= n)
    return long_enough.select(F.explode(runs).alias("g")).select("g.*").groupBy(*names).agg(F.count("*").alias("n"))


@dataclass
class WordModel:
    uni: DataFrame  # w, p1
    bi: DataFrame  # c1, w, n
    bi_ctx: DataFrame  # c1, n1, d1
    tri: DataFrame | None
    tri_ctx: DataFrame | None
    unseen: DataFrame  # one row: the probability of a word that training lacks

    def score(self, rows: DataFrame) -> DataFrame:
        """rows (c2, c1, w, ...) with p: the probability of w."""
        out = rows.join(self.uni, "w", "left").join(F.broadcast(self.unseen), F.lit(True)).join(self.bi_ctx, "c1", "left").join(self.bi.withColumnRenamed("n", "n2"), ["c1", "w"], "left")
        p1 = F.coalesce("p1", F.col("p_unseen"))
        p2 = F.when(F.col("n1").isNull(), p1).otherwise((F.coalesce("n2", F.lit(0)) + F.col("d1") * p1) / (F.col("n1") + F.col("d1")))
        out = out.withColumn("p", p2).drop("n2", "n1", "d1", "p1", "p_unseen")
        if self.tri is not None:
            out = out.join(self.tri_ctx, ["c2", "c1"], "left").join(self.tri.withColumnRenamed("n", "n3"), ["c2", "c1", "w"], "left")
            p3 = F.when(F.col("n2c").isNull(), F.col("p")).otherwise((F.coalesce("n3", F.lit(0)) + F.col("d2c") * F.col("p")) / (F.col("n2c") + F.col("d2c")))
            out = out.withColumn("p", p3).drop("n3", "n2c", "d2c")
        return out


def counts(seq: DataFrame) -> DataFrame:
    """(c2, c1, w, n): every word with the two before it (null where there are none), counted in one pass over the sequences."""
    at = F.transform(F.sequence(F.lit(0), F.size("w") - 1), lambda i: F.struct(F.get("w", i - 2).alias("c2"), F.get("w", i - 1).alias("c1"), F.get("w", i).alias("w")))
    return cut(seq.where(F.size("w") > 0).select(F.explode(at).alias("g")).select("g.*").groupBy("c2", "c1", "w").agg(F.count("*").alias("n")), "word-counts")


def fit(seq: DataFrame, order: int, counted: DataFrame | None = None) -> WordModel:
    """The model of sequences (w), or of their counts where these are known already."""
    t = counts(seq) if counted is None else counted
    uni = t.groupBy("w").agg(F.sum("n").alias("n"))
    totals = uni.agg(F.sum("n").alias("big_n"), F.count("*").alias("big_d"))
    uni = uni.join(F.broadcast(totals), F.lit(True))
    rest = F.col("big_d") / (F.col("big_d") + 1)
    uni = cut(uni.select("w", ((F.col("n") + rest) / (F.col("big_n") + F.col("big_d"))).alias("p1")), "word-uni")
    unseen = cut(totals.select((rest / (F.col("big_n") + F.col("big_d"))).alias("p_unseen")), "word-unseen")
    bi = cut(t.where("c1 IS NOT NULL").groupBy("c1", "w").agg(F.sum("n").alias("n")), "word-bi")
    ctx = cut(bi.groupBy("c1").agg(F.sum("n").alias("n1"), F.count("*").alias("d1")), "word-bi")
    tri = t.where("c2 IS NOT NULL") if order >= 3 else None
    tri_ctx = cut(tri.groupBy("c2", "c1").agg(F.sum("n").alias("n2c"), F.count("*").alias("d2c")), "word-tri") if tri is not None else None
    return WordModel(uni, bi, ctx, tri, tri_ctx, unseen)


MARKS = (".", "!", "?")
QUOTE = '"'
TOP_K = 1000
VARIANTS = ("baseline", "words", "terminated", "no_stop")


def ranked_candidates(model: WordModel, items: DataFrame, top_k: int = TOP_K) -> DataFrame:
    """items (item_id, c2, c1) x the `top_k` likeliest next tokens: (item_id, c2, c1, w, p, rnk), as a table.

    A token that was not seen after c1 ranks among such tokens as its unigram does, and no token ranks below one whose unigram is rarer unless that
    one was seen; so the top_k lie among the followers of c1 and the top_k commonest tokens, whatever the vocabulary.
    """
    top = model.uni.orderBy(F.desc("p1"), "w").limit(top_k).select("w")
    ids = items.select("item_id", "c2", "c1")
    pool = ids.join(model.bi.select("c1", "w"), "c1").select("item_id", "c2", "c1", "w")
    pool = pool.unionByName(ids.join(F.broadcast(top), F.lit(True)).select("item_id", "c2", "c1", "w")).distinct()
    rank = F.row_number().over(Window.partitionBy("item_id").orderBy(F.desc(F.round("p", 12)), "w"))
    return cut(model.score(pool).withColumn("rnk", rank).where(F.col("rnk") <= top_k), "word-candidates")


def terminated(model: WordModel, words: DataFrame) -> DataFrame:
    """words (item_id, c1, w, p) with `lp`: log probability of the word, an optional mark, an optional quote and the end, at its best."""
    start = words.select("item_id", F.col("w").alias("cand"), F.col("c1").alias("c2"), F.col("w").alias("c1"), F.log("p").alias("lp"))

    def step(rows: DataFrame, tokens) -> DataFrame:
        return model.score(rows.withColumn("w", F.explode(F.array(*map(F.lit, tokens))))).withColumn("lp", F.col("lp") + F.log("p")).select("item_id", "cand", "c2", "c1", "w", "lp")

    shift = lambda rows: rows.select("item_id", "cand", F.col("c1").alias("c2"), F.col("w").alias("c1"), "lp")
    one = step(start, (END, *MARKS, QUOTE))
    marked, quoted = one.where(F.col("w").isin(*MARKS)), one.where(F.col("w") == QUOTE)
    two = step(shift(marked), (END, QUOTE))
    three = step(shift(quoted.unionByName(two.where(F.col("w") == QUOTE))), (END,))
    ends = one.unionByName(two).unionByName(three).where(F.col("w") == END)
    return ends.groupBy("item_id", F.col("cand").alias("w")).agg(F.max("lp").alias("lp"))


def predict(model: WordModel, items: DataFrame, variant: str = "baseline", stop: tuple[str, ...] = STOP, found: DataFrame | None = None) -> DataFrame:
    """items (item_id, c2, c1, context array, answer) -> the likeliest last word of each: (item_id, answer, pred).

    baseline: any word, an optional mark and an optional quote, of which leaving both out is always likeliest; words: baseline with words of the context
    only; terminated: baseline, closed by the end token; no_stop: terminated without stop words. Rules hold for the word: it is one of the
    top tokens. `found` is ranked_candidates of the same model and items, where it is known already.
    """
    found = ranked_candidates(model, items) if found is None else found
    pool = found.where(F.col("w").rlike("^[a-z]+$")).select("item_id", "c1", "w", "p")
    if variant == "words":
        pool = pool.join(items.select("item_id", F.explode(F.array_distinct("context")).alias("w")), ["item_id", "w"], "left_semi")
    if variant == "no_stop":
        pool = pool.where(~F.col("w").isin(*stop))
    if variant in ("terminated", "no_stop"):
        # what follows a word only lowers its probability: a word less likely than the best of the first few with their ends can't win
        nth = F.row_number().over(Window.partitionBy("item_id").orderBy(F.desc("p"), "w"))
        pool = cut(pool.withColumn("nth", nth), "word-pool")
        few = cut(terminated(model, pool.where("nth <= 20")), "word-ends")
        bar = few.groupBy("item_id").agg(F.max("lp").alias("bar"))
        more = pool.where("nth > 20").join(F.broadcast(bar), "item_id").where(F.log("p") >= F.col("bar") - 1e-9)
        scored = few.unionByName(terminated(model, more))
    else:
        scored = pool.select("item_id", "w", F.log("p").alias("lp"))
    best = scored.withColumn("r", F.row_number().over(Window.partitionBy("item_id").orderBy(F.desc(F.round("lp", 9)), "w"))).where("r = 1")
    return items.select("item_id", "answer").join(best.select("item_id", F.col("w").alias("pred")), "item_id", "left")


def marked_sequences(docs: DataFrame) -> DataFrame:
    """(doc_id, sent_no, ws, w): English sentences as words, and as words, marks and quotes closed by END. A sentence keeps its mark and a quote after it."""
    s = docs.where("lang = 'en'").select("doc_id", F.posexplode(F.expr(r"""regexp_extract_all(text, '[^.!?\\n|]+[.!?]?"?', 0)""")).alias("sent_no", "s"))
    s = s.select("doc_id", "sent_no", F.expr("regexp_extract_all(lower(s), '[a-z]+', 0)").alias("ws"), F.expr("""regexp_extract_all(lower(s), '[a-z]+|[.!?"]', 0)""").alias("w"))
    return s.where(F.size("ws") > 0).withColumn("w", F.concat("w", F.array(F.lit(END))))
