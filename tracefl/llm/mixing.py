"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree. DataFrame functions only.

Every source gets a target in words: the budget shared by weight, where no source gets
more than ``most_passes`` times its size and the excess is shared anew. A source is cut
into blocks by a hash of its rows and its blocks are permuted by another. Its quota is the number of
draws that reaches the target: all blocks floor(t) times for t passes, then as many of the permuted blocks
as hold the rest of the target (prefix sums over super-blocks, then over the blocks of one super-block,
so no sum runs over more than a share of a hot source).

The quotas are an urn with one colour for each source. A binary tree splits them among the output shards: at
each node, each source's exact quota splits by a multivariate hypergeometric draw (selection sampling in
one row for each node, from seeded hashes). A shard's quota of a source is a range of the source's permuted blocks,
pass after pass; the ranges of the shards are disjoint and meet. A block is taken as often as ranges
hold it, in the shards of those ranges, and not at all if none does. Of the last block of a quota only
the rows up to the target are taken. Within a shard rows are ordered by a hash (the local shuffle).

A block has ``block_words`` words in the mean, or more where all sources together would have over ``MOST_BLOCKS`` blocks; so
an urn has at most 2 * MOST_BLOCKS * most_passes balls and some for each source, at any size.

Defined results: a null text has size 0; a null source is a source of its own, last in order;
equal rows are dealt as one row each; sources without words get target 0; an empty table
gives an empty table. Extra columns are carried along by ``mix``; the columns that it adds,
whose names may get a prefix, replace columns of the same name.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, buckets, hash32, split_join, written

SUPER = 64
MOST_BLOCKS = 1 << 15
ADDED = ("size", "source_size", "target", "taken", "pass_no", "block", "shard", "shard_order")


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def targets(sizes: DataFrame, weights: tuple[int, ...] = (3, 1, 2), budget: tuple[int, int] = (3, 2), most_passes: int = 2) -> DataFrame:
    """(source, source_size, target) from (source, source_size); weights repeat over the sources in code point order, null last.

    The shares that stop at a cap, with the excess shared anew by weight until none is above, are those of one
    level: a source gets least(cap, level * weight). With the sources in order of cap / weight, the level is
    the first at which the next source isn't capped.
    """
    named = Window.orderBy(F.col("source").isNull(), F.encode(F.col("source"), "UTF-8"))
    w = F.element_at(F.array(*[F.lit(x) for x in weights]), (F.pmod(F.row_number().over(named) - 1, F.lit(len(weights))) + 1).cast("int"))
    s = sizes.select("source", "source_size", w.cast("long").alias("w"), (F.col("source_size") * most_passes).alias("cap"))
    by = Window.orderBy((F.col("cap") / F.col("w")), F.col("source").isNull(), F.encode(F.col("source"), "UTF-8"))
    before = by.rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    s = s.withColumn("left", F.sum("source_size").over(whole) * budget[0] / F.lit(budget[1]) - F.coalesce(F.sum("cap").over(before), F.lit(0)))
    s = s.withColumn("open_w", F.sum("w").over(whole) - F.coalesce(F.sum("w").over(before), F.lit(0)))
    s = s.withColumn("try", F.col("left") / F.col("open_w"))
    s = s.withColumn("level", F.min(F.when(F.col("try") * F.col("w") <= F.col("cap"), F.struct((F.col("cap") / F.col("w")).alias("r"), F.col("source").isNull().alias("last"), F.encode(F.col("source"), "UTF-8").alias("s"), "try"))).over(whole)["try"])
    return s.select("source", "source_size", F.when(F.col("level").isNull() | (F.col("level") * F.col("w") >= F.col("cap")), F.col("cap").cast("double")).otherwise(F.col("level") * F.col("w")).alias("target"))


def _narrow(docs: DataFrame, seed: int, text: str, source: str, key: str) -> DataFrame:
    rows = docs.select(F.col(key).alias("doc_id"), F.col(source).alias("source"), word_count(F.col(text)).alias("size"))
    # rows with one key, source and size share their fate, so later joins by these columns are exact; written once
    # (some 20 bytes a row), so that the texts are read once
    rows = rows.groupBy("doc_id", "source", "size").agg(F.count("*").alias("m"))
    return written(rows.withColumn("h", hash32(seed, "row", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")))))


def _blocks(placed: DataFrame, seed: int) -> DataFrame:
    """(source, block, rank, before, full, rest, whole, border): a source's permuted blocks, their place and the words before them; of the last,
    partial pass: whether it takes the block whole, or ends within it. placed: rows with source, sb, block, h, doc_id, size, m, full, rest."""
    sums = placed.groupBy("source", "sb", "block").agg(F.sum(F.col("size") * F.col("m")).alias("words"), F.min(F.struct("h", "doc_id", "size", "m")).alias("lead"), F.first("full").alias("full"), F.first("rest").alias("rest"))
    supers = sums.groupBy("source", "sb").agg(F.sum("words").alias("sb_words"), F.count("*").alias("sb_blocks"))
    ahead = Window.partitionBy("source").orderBy("sb").rowsBetween(Window.unboundedPreceding, -1)
    supers = supers.select("source", "sb", *[F.coalesce(F.sum(c).over(ahead), F.lit(0)).alias(f"{c}_before") for c in ("sb_words", "sb_blocks")])
    order = hash32(seed, "block", F.coalesce(F.col("source"), F.lit("\x00null")), F.col("block"))
    permuted = Window.partitionBy("source", "sb").orderBy("o", "block")
    rows = split_join(sums.withColumn("o", order), supers, ["source", "sb"])
    rows = rows.withColumn("before", F.col("sb_words_before") + F.coalesce(F.sum("words").over(permuted.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    rows = rows.withColumn("rank", F.col("sb_blocks_before") + F.row_number().over(permuted) - 1)
    end = F.col("before") + F.col("words")
    some = F.col("before") + F.col("lead.size") * F.col("lead.m") / 2 <= F.col("rest")  # its first row is taken; no other is without it
    return rows.select("source", "block", "rank", "before", "full", "rest", (end <= F.col("rest")).alias("whole"), ((F.col("before") < F.col("rest")) & (end > F.col("rest")) & some).alias("border"))


def _seat(seed: int, level: int):
    """The step of the draw over one node's colours; its state: balls and left seats that remain, and each colour's count on the left."""

    def colour(acc: Column, x: Column) -> Column:
        def ball(a: Column, i: Column) -> Column:
            u = F.pmod(F.xxhash64(F.lit(seed), F.lit(level), F.col("node"), x["colour"], i), F.lit(1 << 52)) / F.lit(float(1 << 52))
            left = u * a["pool"] < a["seats"]
            return F.struct((a["pool"] - 1).alias("pool"), F.when(left, a["seats"] - 1).otherwise(a["seats"]).alias("seats"), (a["k"] + left.cast("long")).alias("k"))

        balls = F.when(x["n"] > 0, F.sequence(F.lit(1).cast("long"), x["n"])).otherwise(F.array().cast("array<bigint>"))
        end = F.aggregate(balls, F.struct(acc["pool"].alias("pool"), acc["seats"].alias("seats"), F.lit(0).cast("long").alias("k")), ball)
        return F.struct(end["pool"].alias("pool"), end["seats"].alias("seats"), F.array_append(acc["got"], end["k"]).alias("got"))

    return colour


def _splits(quota: DataFrame, levels: int, seed: int) -> DataFrame:
    """(colour, shard, lo, hi): the tree's exact quotas as ranges of each colour's permuted blocks.

    quota: (colour, n). A node is one row with each colour's count. Colours come one after the other, and so
    do a colour's balls: a ball goes left with chance (left seats) / (balls that remain), which draws without replacement.
    """
    node = quota.groupBy().agg(F.array_sort(F.collect_list(F.struct("colour", "n"))).alias("c")).select(F.lit(0).cast("long").alias("node"), F.transform("c", lambda x: F.struct(x["colour"].alias("colour"), x["n"].alias("n"), F.lit(0).cast("long").alias("lo"))).alias("c"))
    for level in range(levels):
        total = F.aggregate("c", F.lit(0).cast("long"), lambda acc, x: acc + x["n"])
        start = F.struct(total.alias("pool"), F.floor((total + 1) / 2).cast("long").alias("seats"), F.array().cast("array<bigint>").alias("got"))

        node = node.withColumn("left", F.aggregate("c", start, _seat(seed, level))["got"])
        pick = lambda right: F.zip_with("c", "left", lambda x, k: F.struct(x["colour"].alias("colour"), (x["n"] - k if right else k).alias("n"), (x["lo"] + k if right else x["lo"]).alias("lo")))
        node = node.select(F.explode(F.array(F.struct((F.col("node") * 2).alias("node"), pick(False).alias("c")), F.struct((F.col("node") * 2 + 1).alias("node"), pick(True).alias("c")))).alias("x")).select("x.*")
    return node.select("node", F.explode("c").alias("x")).select(F.col("x.colour").alias("colour"), F.col("node").alias("shard"), F.col("x.lo").alias("lo"), (F.col("x.lo") + F.col("x.n")).alias("hi"))


def _draws(blocks: DataFrame, levels: int, seed: int) -> DataFrame:
    """(source, block, before, draws): the draws of a block, from the shards' ranges of its source's permuted blocks; `part` marks one that takes some rows only."""
    colour = F.coalesce(F.col("source"), F.lit("\x00null"))
    quota = blocks.groupBy(colour.alias("colour")).agg(F.count("*").alias("n_blocks"), (F.first("full") * F.count("*") + F.sum((F.col("whole") | F.col("border")).cast("long"))).alias("n"))
    quota = written(quota)  # a row for each source
    ranges = _splits(quota.select("colour", "n"), levels, seed)
    ranges = ranges.groupBy("colour").agg(F.array_sort(F.collect_list(F.struct("lo", "hi", "shard"))).alias("ranges"))  # one for each shard
    held = split_join(split_join(blocks.withColumn("colour", colour), quota.drop("n"), ["colour"]), ranges, ["colour"])

    def draw(p: Column) -> Column:
        at = p * F.col("n_blocks") + F.col("rank")
        hit = F.filter("ranges", lambda x: (x["lo"] <= at) & (at < x["hi"]))
        return F.struct((p + 1).alias("pass_no"), F.get(hit, F.lit(0))["shard"].alias("shard"), (F.col("border") & (p == F.col("full"))).alias("part"))

    every = F.transform(F.sequence(F.lit(0).cast("long"), F.col("full")), draw)
    return held.select("source", "block", "before", F.filter(every, lambda x: x["shard"].isNotNull()).alias("draws"))


def deal(docs: DataFrame, levels: int = 3, seed: int = 17, block_words: int = 1 << 15, text: str = "text", source: str = "source", key: str = "doc_id", **shares) -> DataFrame:
    """Each distinct (doc_id, source, size), of which there are m rows, with source_size, target, block and its draws: (pass_no, shard, part)."""
    rows = _narrow(docs, seed, text, source, key)
    goal = targets(rows.groupBy("source").agg(F.sum(F.col("size") * F.col("m")).alias("source_size")), **shares)
    # blocks of a source: a power of two, by the leading bits of the rows' hash
    mean = F.greatest(F.lit(float(block_words)), F.sum("source_size").over(Window.partitionBy()) / F.lit(float(MOST_BLOCKS)))
    bits = F.greatest(F.lit(0), F.least(F.lit(31), F.ceil(F.log2(F.greatest(F.lit(1.0), F.col("source_size") / mean)))))
    goal = goal.select("*", bits.cast("int").alias("bits"), F.least(F.col("target") / F.greatest(F.col("source_size"), F.lit(1)), F.lit(1e6)).alias("passes"))
    goal = goal.select("*", F.floor("passes").cast("long").alias("full")).withColumn("rest", F.col("target") - F.col("full") * F.col("source_size"))
    goal = written(goal.select("source", "source_size", "target", "bits", "full", "rest"))  # a row for each source; several branches use it
    # each row of `goal` stands for a source; the rows of a hot source are dealt by their block
    placed = split_join(rows, goal, ["source"]).withColumn("block", F.expr("shiftright(h, 32 - bits)"))
    placed = placed.withColumn("sb", F.pmod(hash32(seed, "super", F.col("block")), F.lit(SUPER)).cast("int"))
    draws = written(_draws(written(_blocks(placed, seed)), levels, seed))  # a row for each block
    drawn = split_join(placed, draws, ["source", "block"]).withColumn("cut", F.exists("draws", lambda x: x["part"]))
    # rows of the blocks that are drawn in part, one block a source at most: taken while that brings the sum nearer to the target
    w_row = Window.partitionBy("source", "block").orderBy("h", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    cut = drawn.where("cut").withColumn("sofar", F.col("before") + F.coalesce(F.sum(F.col("size") * F.col("m")).over(w_row), F.lit(0)))
    cut = cut.withColumn("in", F.col("sofar") + F.col("size") * F.col("m") / 2 <= F.col("rest"))
    cut = cut.withColumn("draws", F.filter("draws", lambda x: ~x["part"] | F.col("in"))).drop("sofar", "in")
    return drawn.where("not cut").unionByName(cut).select("doc_id", "source", "size", "m", "source_size", "target", "block", "draws")


def taken(docs: DataFrame, **how) -> DataFrame:
    """Each row of docs without its text: doc_id, source, size, source_size, target, the words that the mix takes of it, and the shards where."""
    out = deal(docs, **how).withColumn("_", F.explode(F.sequence(F.lit(1).cast("long"), F.col("m"))))
    return out.select("doc_id", "source", "size", "source_size", "target", (F.col("size") * F.size("draws")).alias("taken"), F.array_sort(F.col("draws.shard")).alias("shards"))


def mix(docs: DataFrame, levels: int = 3, seed: int = 17, block_words: int = 1 << 15, text: str = "text", source: str = "source", key: str = "doc_id", prefix: str = "", **shares) -> DataFrame:
    """docs in the mix: one row for each time a row is taken, with its pass, block, shard (of 2**levels) and place there."""
    dealt = deal(docs, levels, seed, block_words, text, source, key, **shares)
    dealt = dealt.withColumn("taken", F.col("size") * F.size("draws")).withColumn("draw", F.explode("draws")).select("*", "draw.pass_no", "draw.shard")
    dealt = dealt.withColumn("shard_order", hash32(seed, "shuffle", F.col("doc_id"), F.col("pass_no")))
    dealt = dealt.select(F.col("doc_id").alias("__k"), F.col("source").alias("__s"), F.col("size").alias("__n"), *[F.col(c).alias(prefix + c) for c in ADDED])
    kept = docs.select(*[F.col(f"`{c}`") for c in docs.columns if c not in {prefix + a for a in ADDED}], F.col(key).alias("__k"), F.col(source).alias("__s"), word_count(F.col(text)).alias("__n"))
    return split_join(kept, dealt, ["__k", "__s", "__n"]).drop("__k", "__s", "__n")


def in_order(mixed: DataFrame, prefix: str = "") -> DataFrame:
    """The mix as it is to be written: shard after shard in their order, over range partitions, so a large shard spans several files."""
    by = [prefix + "shard", prefix + "shard_order"]
    return mixed.repartitionByRange(buckets(mixed.sparkSession), *by).sortWithinPartitions(*by)
