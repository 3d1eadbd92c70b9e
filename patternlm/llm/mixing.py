"""Mixing sources to target weights (built-in functions only).

Each source's words form one sequence, cut into blocks of `block` words (the last may be shorter). A source whose target is e times its
size plus R words needs e*blocks + ceil(R/block) slots of the output. Output shards have `shard_slots` slots; the source of each slot is drawn
independently with the targets as probabilities, so a shard's counts by source are multinomial. The j-th slot that a source drew, over all
shards, reads block perm(j mod blocks) of epoch j div blocks, perm being a pseudorandom permutation keyed by source and epoch (swap-or-not
rounds: exact on any domain, no tables, the same on every rerun). Draws beyond what a source needs free their slots, and what other sources
lack to their targets fills these, so every total meets its target to the word. Blocks join documents by (source, index).

Targets: sources by code point, null last, weigh 5, 2, 1, repeating; a target stops at 3 times its source's size and the excess goes
to the others by weight (water filling). Null text has size 0 and takes 0. Repeated rows count each by itself; empty input gives an
empty result; extra columns are ignored, whatever their names. No row's taken words exceed 3 times its size, since no epoch reads a block twice.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from patternlm.llm.common import column, let, n_words, whole_row, words
from patternlm.session import cut

WEIGHTS = (5, 2, 1)
MOST_REPEATS = 3
BLOCK = 256
SHARD_SLOTS = 4096
ROUNDS = 24
CELL = 256
LEAST_CHUNK = 512  # rows of a chunk of a source's sequence, at least
SUPER = 1024  # shards that are summed together


def permuted(x: Column, n: Column, key: Sequence[Column], inverse: bool = False) -> Column:
    """Swap-or-not: a keyed permutation of 0..n-1; each round is its own inverse, so the inverse runs them backwards."""
    rounds = F.sequence(F.lit(ROUNDS - 1), F.lit(0), F.lit(-1)) if inverse else F.sequence(F.lit(0), F.lit(ROUNDS - 1))

    def step(at: Column, r: Column) -> Column:
        partner = F.pmod(F.pmod(F.xxhash64(*key, r), n) - at, n)
        return F.when(F.xxhash64(*key, r, F.greatest(at, partner), F.lit("swap")).bitwiseAND(F.lit(1)) == 1, partner).otherwise(at)

    return F.aggregate(rounds, x.cast("long"), step)


def source_key(source: Column) -> Column:
    return F.when(source.isNull(), F.lit("0")).otherwise(F.concat(F.lit("1"), source.cast("string")))


def sizes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """A narrow row for the documents of equal id, text and source: how many (`copies`), their size, and a digest that orders ties."""
    text = F.coalesce(column(text_col), F.lit(""))
    base = docs.select(column(id_col).cast("long").alias("doc_id"), column(source_col).cast("string").alias("source"), n_words(column(text_col)).alias("size"), F.xxhash64(text).alias("digest"))
    return base.groupBy("doc_id", "source", "size", "digest").agg(F.count("*").alias("copies")).withColumn("skey", source_key(F.col("source")))


def targets(sized: DataFrame, weights: Sequence[int] = WEIGHTS, most: int = MOST_REPEATS) -> DataFrame:
    """A row per source: size, weight, target. Works on one pre-aggregated row per source."""
    by = sized.groupBy("skey", "source").agg(F.sum(F.col("size") * F.col("copies")).alias("source_size"))
    turn = F.row_number().over(Window.orderBy(F.col("source").isNull(), "source")) - 1
    by = by.withColumn("turn", turn).withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), F.pmod("turn", F.lit(len(weights))) + 1).cast("double"))
    level = F.col("source_size") * most / F.col("weight")
    order = Window.orderBy(F.col("level"), F.col("turn"))
    upto, onward = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing)
    by = by.withColumn("level", level).withColumn("capped", F.coalesce(F.sum("source_size").over(upto), F.lit(0)) * most)
    by = by.withColumn("open_weight", F.sum("weight").over(onward)).withColumn("total", F.sum("source_size").over(Window.partitionBy()))
    by = by.withColumn("rate", (F.col("total") - F.col("capped")) / F.col("open_weight")).withColumn("place", F.row_number().over(order))
    rate = F.min_by(F.when(F.col("level") >= F.col("rate"), F.col("rate")), F.when(F.col("level") >= F.col("rate"), F.col("place"))).over(Window.partitionBy())
    target = F.least((F.col("source_size") * most).cast("double"), F.col("weight") * F.coalesce(rate, F.lit(0.0)))
    return by.select("skey", "source", "source_size", "weight", target.alias("target"))


def plan(per_source: DataFrame, block: int = BLOCK) -> DataFrame:
    """Adds blocks, whole epochs, words and slots of the last epoch, and the source's range of slots."""
    size, want = F.col("source_size"), F.round("target").cast("long")
    p = per_source.where("source_size > 0").withColumn("blocks", F.ceil(size / block).cast("long")).withColumn("epochs", F.floor(want / size).cast("long"))
    p = p.withColumn("rest", want - F.col("epochs") * size).withColumn("last_len", size - (F.col("blocks") - 1) * block)
    p = p.withColumn("rest_slots", F.when(F.col("rest") == 0, F.lit(0)).otherwise(F.least(F.col("blocks"), F.ceil(F.col("rest") / block) + 1)).cast("long"))
    p = p.withColumn("slots", F.col("epochs") * F.col("blocks") + F.col("rest_slots"))
    p = p.withColumn("short_pos", permuted(F.col("blocks") - 1, F.col("blocks"), [F.col("skey"), F.col("epochs")], inverse=True))
    hi = F.sum("slots").over(Window.orderBy("skey").rowsBetween(Window.unboundedPreceding, 0))
    return p.withColumn("hi", hi).withColumn("lo", F.col("hi") - F.col("slots"))


def draws(planned: DataFrame, shard_slots: int = SHARD_SLOTS, seed: int = 0) -> DataFrame:
    """(shard, slot, skey): every slot with its source, drawn by the sources' shares of all slots; shards have multinomial counts."""
    spark = planned.sparkSession
    total = planned.agg(F.max("hi")).first()[0] or 0  # one number
    # a source's range is cut into cells, so that slots find their source by an equi-join, whatever the number of sources
    cells = planned.where("slots > 0").select("skey", "lo", "hi", F.explode(F.sequence(F.expr(f"lo div {CELL}"), F.expr(f"(hi - 1) div {CELL}"))).alias("cell"))
    drawn = spark.range(total).select(F.col("id").alias("slot"), F.pmod(F.xxhash64(F.lit(seed), F.lit("draw"), "id"), F.lit(max(total, 1))).alias("u"))
    drawn = drawn.withColumn("cell", F.expr(f"u div {CELL}")).join(cells, "cell").where("u >= lo AND u < hi")
    return drawn.select(F.expr(f"slot div {shard_slots}").alias("shard"), "slot", "skey")


def shard_counts(dealt: DataFrame) -> DataFrame:
    """Slots by shard and source, and their words where slots have a take."""
    words_ = [F.sum("take").alias("words")] if "take" in dealt.columns else []
    return dealt.groupBy("shard", "skey").agg(F.count("*").alias("slots"), *words_)


def _before(w):
    return w.rowsBetween(Window.unboundedPreceding, -1)


def numbered(drawn: DataFrame) -> DataFrame:
    """drawn with `j`: how many slots the source drew before, by sums over groups of shards, shards and slots."""
    counts = shard_counts(drawn).withColumn("many", F.expr(f"shard div {SUPER}"))
    groups = counts.groupBy("skey", "many").agg(F.sum("slots").alias("held"))
    groups = groups.select("skey", "many", F.coalesce(F.sum("held").over(_before(Window.partitionBy("skey").orderBy("many"))), F.lit(0)).alias("base"))
    inside = F.coalesce(F.sum("slots").over(_before(Window.partitionBy("skey", "many").orderBy("shard"))), F.lit(0))
    base = counts.withColumn("inside", inside).join(groups, ["skey", "many"]).select("skey", "shard", (F.col("base") + F.col("inside")).alias("base"))
    nth = drawn.withColumn("nth", F.row_number().over(Window.partitionBy("shard", "skey").orderBy("slot")) - 1)
    return nth.join(base, ["skey", "shard"]).select("shard", "slot", "skey", (F.col("base") + F.col("nth")).alias("j"))


def settled(ranked: DataFrame, planned: DataFrame, shard_slots: int = SHARD_SLOTS) -> DataFrame:
    """(shard, slot, skey, j) with every j below what its source needs: slots drawn beyond that go to sources that drew too few."""
    need = planned.select("skey", F.col("slots").alias("need"))
    held = ranked.join(need, "skey")
    got = ranked.groupBy("skey").agg(F.count("*").alias("got"))
    lacking = need.join(got, "skey", "left").withColumn("got", F.coalesce("got", F.lit(0))).where("need > got")
    first = F.coalesce(F.sum(F.col("need") - F.col("got")).over(_before(Window.orderBy("skey"))), F.lit(0))
    lacking = lacking.withColumn("first", first).select("skey", "first", "got", F.explode(F.sequence(F.col("got"), F.col("need") - 1)).alias("j"))
    lacking = lacking.select("skey", "j", (F.col("first") + F.col("j") - F.col("got")).alias("nth"))
    free = held.where("j >= need").select("shard", "slot")  # the last draws of some sources: in few shards
    per = free.groupBy("shard").agg(F.count("*").alias("n"))
    base = per.select("shard", F.coalesce(F.sum("n").over(_before(Window.orderBy("shard"))), F.lit(0)).alias("base"))
    places = free.withColumn("k", F.row_number().over(Window.partitionBy("shard").orderBy("slot")) - 1).join(base, "shard")
    filled = places.select("shard", "slot", (F.col("base") + F.col("k")).alias("nth")).join(lacking, "nth").select("shard", "slot", "skey", "j")
    return held.where("j < need").select("shard", "slot", "skey", "j").unionByName(filled)


def slots(planned: DataFrame, block: int = BLOCK, shard_slots: int = SHARD_SLOTS, seed: int = 0) -> DataFrame:
    """Every output slot: shard, slot, source, epoch, block index, and the words it takes of the block."""
    ranked = cut(numbered(cut(draws(planned, shard_slots, seed), "mix-draws")), "mix-numbered")
    dealt = settled(ranked, planned, shard_slots).join(planned, "skey")
    dealt = dealt.withColumn("epoch", F.expr("j div blocks")).withColumn("pos", F.expr("j % blocks"))
    dealt = dealt.withColumn("block", permuted(F.col("pos"), F.col("blocks"), [F.col("skey"), F.col("epoch")]))
    whole = F.when(F.col("block") == F.col("blocks") - 1, F.col("last_len")).otherwise(F.lit(block))
    before = F.col("pos") * block - F.when(F.col("pos") > F.col("short_pos"), F.lit(block) - F.col("last_len")).otherwise(F.lit(0))
    take = F.when(F.col("epoch") < F.col("epochs"), whole).otherwise(F.greatest(F.lit(0), F.least(whole, F.col("rest") - before)))
    return dealt.select("shard", "slot", "skey", "source", "epoch", "block", take.cast("long").alias("take"), (F.col("epoch") < F.col("epochs")).alias("whole"))


def laid_out(sized: DataFrame) -> DataFrame:
    """A row for each document with `start`: the words of the source before it. Chunks of a source are summed first, so no source needs one task."""
    n = sized.count()
    chunks = max(1, -(-n // max(LEAST_CHUNK, math.isqrt(n))))
    sized = sized.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "digest"), F.lit(chunks))).withColumn("all", F.col("size") * F.col("copies"))
    held = sized.groupBy("skey", "chunk").agg(F.sum("all").alias("held"))
    base = held.select("skey", "chunk", F.coalesce(F.sum("held").over(_before(Window.partitionBy("skey").orderBy("chunk"))), F.lit(0)).alias("base"))
    inside = F.coalesce(F.sum("all").over(_before(Window.partitionBy("skey", "chunk").orderBy("doc_id", "digest", "size"))), F.lit(0))
    placed = sized.withColumn("inside", inside).join(base, ["skey", "chunk"])
    placed = placed.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))))
    return placed.withColumn("start", F.col("base") + F.col("inside") + (F.col("copy") - 1) * F.col("size")).select("doc_id", "digest", "copy", "skey", "source", "size", "start")


def spread_over_blocks(sized: DataFrame, block: int) -> DataFrame:
    """A row for each document and block of it (block null where it has no words): begin and overlap, in words of the document."""
    first, last = F.expr(f"start div {block}"), F.expr(f"(start + size - 1) div {block}")
    spread = laid_out(sized).select("*", F.explode_outer(F.when(F.col("size") > 0, F.sequence(first, last))).alias("block"))
    begin, end = F.greatest(F.col("start"), F.col("block") * block), F.least(F.col("start") + F.col("size"), (F.col("block") + 1) * block)
    return spread.withColumn("begin", begin - F.col("start")).withColumn("overlap", end - begin)


def segments(docs: DataFrame, block: int = BLOCK, weights: Sequence[int] = WEIGHTS, most: int = MOST_REPEATS, shard_slots: int = SHARD_SLOTS, seed: int = 0, **columns) -> DataFrame:
    """spread_over_blocks with how often the whole overlap is taken (`uses`), the words of a last, partial use (`part`), and the shards of both."""
    sized = cut(sizes(docs, **columns), "mix-sizes")
    per_source = cut(targets(sized, weights, most), "mix-targets")
    dealt = slots(cut(plan(per_source, block), "mix-plan"), block, shard_slots, seed)
    use = dealt.groupBy("skey", "block").agg(
        F.sum(F.col("whole").cast("long")).alias("uses"), F.max(F.when(~F.col("whole"), F.col("take")).otherwise(0)).alias("part_take"), F.collect_set("shard").alias("shards"))  # at most `most` slots a block
    met = spread_over_blocks(sized, block).join(use, ["skey", "block"], "left").join(per_source.select("skey", "source_size", "target"), "skey")
    part = F.greatest(F.lit(0), F.least(F.col("overlap"), F.coalesce("part_take", F.lit(0)) - (F.col("start") + F.col("begin") - F.col("block") * block)))
    return met.withColumn("part", F.coalesce(part, F.lit(0))).withColumn("uses", F.coalesce("uses", F.lit(0)))


ROW = ("doc_id", "digest", "copy", "skey")


def mix(docs: DataFrame, **options) -> DataFrame:
    """Every row of docs: doc_id, size, source_size, target, taken (and its source, and the output shards that its blocks went to, in order)."""
    took = F.coalesce(F.sum(F.col("overlap") * F.col("uses") + F.col("part")), F.lit(0)).cast("long")
    went = F.array_sort(F.array_distinct(F.flatten(F.collect_list(F.when(F.col("uses") + F.col("part") > 0, F.col("shards"))))))  # of a document's own blocks
    by = segments(docs, **options).groupBy(*ROW, "source", "size", "source_size", "target").agg(took.alias("taken"), went.alias("shards"))
    return by.select("doc_id", "source", "size", "source_size", "target", "taken", "shards")


def mixed_blocks(docs: DataFrame, block: int = BLOCK, weights: Sequence[int] = WEIGHTS, most: int = MOST_REPEATS, shard_slots: int = SHARD_SLOTS, seed: int = 0, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The mix itself: (shard, slot, source, epoch, block, text, doc_ids), a row for each slot; text is the words that it takes, joined by single spaces."""
    names = {"id_col": id_col, "text_col": text_col, "source_col": source_col}
    sized = cut(sizes(docs, **names), "mix-sizes")
    dealt = slots(cut(plan(cut(targets(sized, weights, most), "mix-targets"), block), "mix-plan"), block, shard_slots, seed)
    texts = docs.select(column(id_col).cast("long").alias("doc_id"), source_key(column(source_col).cast("string")).alias("skey"), F.xxhash64(F.coalesce(column(text_col), F.lit(""))).alias("digest"), column(text_col).alias("text"))
    texts = texts.dropDuplicates(["doc_id", "skey", "digest"])
    met = spread_over_blocks(sized, block).where("size > 0").alias("s").join(texts.alias("t"), F.col("s.doc_id").eqNullSafe(F.col("t.doc_id")) & (F.col("s.skey") == F.col("t.skey")) & (F.col("s.digest") == F.col("t.digest")))
    part = let(words(F.col("text")), lambda w: F.slice(w, F.col("begin").cast("int") + 1, F.col("overlap").cast("int")))
    held = met.select("s.skey", "block", F.struct("start", F.col("s.doc_id").alias("doc_id"), part.alias("w")).alias("part")).groupBy("skey", "block").agg(F.sort_array(F.collect_list("part")).alias("parts"))  # a block's own words
    whole = held.select("skey", "block", F.flatten(F.transform("parts", lambda p: p["w"])).alias("w"), F.transform("parts", lambda p: p["doc_id"]).alias("doc_ids"))
    return dealt.join(whole, ["skey", "block"]).select("shard", "slot", "source", "epoch", "block", F.array_join(F.slice("w", F.lit(1), F.col("take").cast("int")), " ").alias("text"), "doc_ids")


def mixed_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **options) -> DataFrame:
    """The mix as documents: a row for each whole use of a document, and one that joins the words of its partial uses.

    A document is used as often as each of its blocks is; words that only some blocks give are joined by single spaces in one more row.
    Rows of equal id, text and source are told apart by their other columns (but for maps).
    """
    by = segments(docs, id_col=id_col, text_col=text_col, source_col=source_col, **options).groupBy(*ROW, "size").agg(
        F.min("uses").alias("whole"),
        F.sort_array(F.collect_list(F.struct("begin", "overlap", "uses", "part"))).alias("segments"),  # a document's own blocks
    )
    key = by.select(F.col("doc_id").alias("k_id"), F.col("digest").alias("k_digest"), F.col("skey").alias("k_skey"), F.col("copy").alias("k_copy"), "whole", "segments").where("size > 0")
    rows = docs.select(whole_row(docs).alias("row"), column(id_col).cast("long").alias("id"), column(text_col).alias("text"), source_key(column(source_col).cast("string")).alias("skey"), F.xxhash64(F.coalesce(column(text_col), F.lit(""))).alias("digest"))
    plain = [F.col("row")[f.name] for f in docs.schema.fields if "map<" not in f.dataType.simpleString() and "variant" not in f.dataType.simpleString()]
    rows = rows.withColumn("copy", F.row_number().over(Window.partitionBy("id", "digest", "skey").orderBy(F.xxhash64(*plain))))
    met = rows.join(key, rows["id"].eqNullSafe(key["k_id"]) & (F.col("digest") == F.col("k_digest")) & (F.col("skey") == F.col("k_skey")) & (F.col("copy") == F.col("k_copy")))

    def pieces(w: Column) -> Column:
        extra = lambda s: F.concat(F.array_repeat(F.slice(w, s["begin"].cast("int") + 1, s["overlap"].cast("int")), (s["uses"] - F.col("whole")).cast("int")), F.array(F.slice(w, s["begin"].cast("int") + 1, s["part"].cast("int"))))
        return F.flatten(F.flatten(F.transform(F.col("segments"), extra)))

    partial = let(let(words(F.col("text")), pieces), lambda p: F.when(F.size(p) > 0, F.array(F.array_join(p, " "))).otherwise(F.array().cast("array<string>")))
    out = met.select("row", F.explode(F.concat(F.array_repeat(F.col("text"), F.col("whole").cast("int")), partial)).alias("out"))
    return out.select(*(F.col("out").alias(c) if c == text_col else F.length("out").cast("long").alias(c) if c == "n_chars" else F.col("row")[c].alias(c) for c in docs.columns))
