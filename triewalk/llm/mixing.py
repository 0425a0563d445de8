"""Mixing sources to target weights by Sainte-Lague apportionment of equal-token blocks.

Each source's documents stand in a seeded order; the words of that order are cut into blocks of equal size. The blocks of
the mix are awarded one by one to the source with the highest quotient target / (2 awards + 1); the awards, in that order,
are cut into shards of equal numbers of blocks, so every shard has integer quotas per source. An award takes the source's
next block in a seeded order of blocks; when all are taken, the next round begins, three rounds at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize
from .ranks import running_start, sent_if_small

#: Blocks of a mix, whatever its size: bounds the award table and what is broadcast (a few MB).
BLOCKS = 1 << 16
BUCKETS = 1024
SHARDS = 16
WEIGHTS = (5.0, 2.0, 1.0)
MOST_COPIES = 3
#: Shares of a document are counted in units of 1 / WHOLE; size classes are half powers of two.
WHOLE = 1 << 20
SIZE_CLASSES = 64
WORD = r"[^\x20\x09-\x0D]+"


def sized(docs: DataFrame, id_col: str, text_col: str, source_col: str) -> DataFrame:
    return docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("long").alias("size"))


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS) -> DataFrame:
    """source, source_size, target: every source's share of all words by weight, no more than three times its own words.

    The level at which uncapped sources share what is left is found in closed form over one row a source,
    in ascending order of the level at which each meets its cap.
    """
    per = sizes.groupBy("source").agg(F.sum("size").cast("long").alias("source_size"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())  # one row a source
    weight = F.element_at(F.array(*(F.lit(w) for w in weights)), F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights))).cast("int") + 1)
    per = per.withColumn("weight", weight).withColumn("cap", F.col("source_size") * MOST_COPIES).withColumn("meets", F.col("cap") / F.col("weight"))
    up = Window.orderBy("meets", F.col("source").asc_nulls_last())
    before = up.rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    left_words = F.sum("source_size").over(whole) - F.coalesce(F.sum("cap").over(before), F.lit(0))
    left_weight = F.sum("weight").over(whole) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))
    per = per.withColumn("level", left_words / left_weight)
    level = F.min(F.when(F.col("meets") >= F.col("level"), F.struct("meets", F.col("source").isNull(), "source", "level"))).over(whole)
    return per.select("source", "source_size", "weight", F.coalesce(F.least(F.col("cap").cast("double"), level["level"] * F.col("weight")), F.col("cap").cast("double")).alias("target"))


def _in_blocks(targets: DataFrame, blocks: int) -> DataFrame:
    """targets with total, block (words of a block) and n_blocks, sources of no words left out."""
    t = targets.withColumn("total", F.sum("source_size").over(Window.partitionBy()))
    t = t.withColumn("block", F.greatest(F.ceil(F.col("total") / blocks).cast("long"), F.lit(1)))
    return t.withColumn("n_blocks", F.ceil(F.col("source_size") / F.col("block")).cast("long")).where("source_size > 0")


def awards(targets: DataFrame, blocks: int = BLOCKS, shards: int = SHARDS) -> DataFrame:
    """source, award, n_blocks, shard: the blocks of the mix in order of quotient, cut into shards of equal numbers of blocks."""
    t = _in_blocks(targets, blocks)
    most = F.least(F.ceil(F.col("target") / F.col("block")).cast("long") + 1, F.col("n_blocks") * MOST_COPIES)
    claims = t.select("source", "block", "n_blocks", "total", F.col("target"), F.explode(F.sequence(F.lit(0), most - 1)).alias("award"))
    claims = claims.withColumn("quotient", F.col("target") / (2 * F.col("award") + 1))
    # blocks + 2 rows a source at most
    rank = F.row_number().over(Window.orderBy(F.col("quotient").desc(), F.col("source").asc_nulls_last(), "award"))
    house = F.ceil(F.col("total") / F.col("block"))
    won = claims.withColumn("rank", rank).where(F.col("rank") <= house)
    return won.select("source", "award", "n_blocks", F.floor((F.col("rank") - 1) * shards / house).cast("int").alias("shard"))


def shard_quotas(docs: DataFrame, text_col: str = "text", source_col: str = "source", weights: tuple[float, ...] = WEIGHTS, blocks: int = BLOCKS, shards: int = SHARDS) -> DataFrame:
    """source, shard, blocks: how many blocks of each source the mix puts in each shard; a shard's quotas add up to its blocks.

    Sources of no words have none. An empty table gives an empty result.
    """
    targets = source_targets(sized(docs, source_col, text_col, source_col), weights)
    return awards(materialize(targets, "mix-targets"), blocks, shards).groupBy("source", "shard").agg(F.count(F.lit(1)).alias("blocks"))


def award_blocks(targets: DataFrame, seed: int, blocks: int = BLOCKS, shards: int = SHARDS) -> DataFrame:
    """source, block_no (in the source's order of words), times, shards: the blocks that fill the quotas, in a seeded order, and how often."""
    order = Window.partitionBy("source").orderBy(F.xxhash64(F.lit(seed), F.coalesce("source", F.lit("")), "block_no"), "block_no")
    deck = _in_blocks(targets, blocks).select("source", F.explode(F.sequence(F.lit(0), F.col("n_blocks") - 1)).alias("block_no")).withColumn("place", F.row_number().over(order) - 1)
    won = awards(targets, blocks, shards).select(F.col("source").alias("s"), F.pmod("award", "n_blocks").alias("p"), "shard")
    taken = deck.join(won, F.col("source").eqNullSafe(F.col("s")) & (F.col("place") == F.col("p")), "left")
    return taken.groupBy("source", "block_no").agg(F.count("p").cast("long").alias("times"), F.sort_array(F.collect_list("shard")).alias("shards"))


def mix(docs: DataFrame, seed: int = 7, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[float, ...] = WEIGHTS, blocks: int = BLOCKS) -> DataFrame:
    """doc_id, size, source_size, target, taken for every row of docs: taken counts the words of the row that the mix holds, repeats included.

    Size: words of the text (null or empty: 0). A null source is a source, last in order. Rows of no words take nothing.
    Rows that are the same are interchangeable. Tables of a row a source, or of 1024, are broadcast if a count shows them small. An empty table gives an empty result. Other columns are not read.
    """
    return mixed_rows(docs, seed, id_col, text_col, source_col, weights, blocks).drop("source")


def mixed_rows(docs: DataFrame, seed: int, id_col: str, text_col: str, source_col: str, weights: tuple[float, ...] = WEIGHTS, blocks: int = BLOCKS) -> DataFrame:
    """The rows of mix, with their source."""
    rows = materialize(sized(docs, id_col, text_col, source_col), "mix-sizes")
    targets = materialize(source_targets(rows, weights), "mix-targets")
    plan = award_blocks(targets, seed, blocks)
    before = Window.partitionBy("source").orderBy("block_no").rowsBetween(Window.unboundedPreceding, -1)
    plan = plan.withColumn("chosen_before", F.coalesce(F.sum("times").over(before), F.lit(0))).select("source", "block_no", "times", "chosen_before")
    plan = materialize(plan, "mix-plan")
    sources = targets.count()

    total = Window.partitionBy()
    t = targets.withColumn("block", F.greatest(F.ceil(F.sum("source_size").over(total) / blocks).cast("long"), F.lit(1)))
    t = t.select(F.col("source").alias("ts"), "source_size", "target", "block")
    mixed = F.xxhash64(F.lit(seed), "doc_id")
    placed = running_start(rows, ["source"], F.pmod(mixed, F.lit(BUCKETS)), [mixed, F.col("doc_id"), F.col("size")], F.col("size"), BUCKETS, "begin", sources)
    placed = placed.join(sent_if_small(t, sources), F.col("source").eqNullSafe(F.col("ts")), "left").withColumn("end", F.col("begin") + F.col("size"))
    first, last = F.floor(F.col("begin") / F.col("block")), F.floor((F.col("end") - 1) / F.col("block"))
    for at, block in (("a", first), ("z", last)):
        right = plan.select(F.col("source").alias(f"s_{at}"), F.col("block_no").alias(f"k_{at}"), F.col("times").alias(f"times_{at}"), F.col("chosen_before").alias(f"chosen_{at}"))
        placed = placed.withColumn(f"b_{at}", block).join(sent_if_small(right, blocks + sources), F.col("source").eqNullSafe(F.col(f"s_{at}")) & (F.col(f"b_{at}") == F.col(f"k_{at}")), "left")
    upto = lambda at, x: F.col(f"chosen_{at}") * F.col("block") + F.col(f"times_{at}") * (F.col(x) - F.col(f"b_{at}") * F.col("block"))
    taken = F.when(F.col("size") > 0, upto("z", "end") - upto("a", "begin")).otherwise(0)
    return placed.select("doc_id", "source", "size", "source_size", "target", F.coalesce(taken, F.lit(0)).cast("long").alias("taken"))


def repeat_mixed(docs: DataFrame, seed: int = 7, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The rows of docs as often as the mix takes them, in whole documents, all columns as they are.

    A source's documents stand in order of size class; the shares taken / size are summed up in that order, and a document
    comes as often as the sum, from one half on, passes a whole number. So the copies of any run of the order are right to one, and as
    sizes hardly differ along it, a source's words come to what the mix takes, whatever the size of blocks and documents.
    Rows of no words stay out. Rows that repeat id and source count as one document, of all their words.
    """
    rows = mixed_rows(docs, seed, id_col, text_col, source_col).where("size > 0")
    each = rows.groupBy("doc_id", "source").agg(F.sum("size").alias("size"), F.sum("taken").alias("taken"))
    each = materialize(each.withColumn("share", F.round(F.col("taken") * F.lit(float(WHOLE)) / F.col("size")).cast("long")), "mix-shares")
    sources = each.agg(F.count_distinct("source")).first()[0] + 1
    mixed = F.xxhash64(F.lit(seed), "doc_id")
    size_class = F.least(F.floor(2 * F.log2("size")), F.lit(SIZE_CLASSES - 1))
    per_class = BUCKETS // SIZE_CLASSES
    summed = running_start(each, ["source"], size_class * per_class + F.pmod(mixed, F.lit(per_class)), [mixed, F.col("doc_id")], F.col("share"), BUCKETS, "begin", sources)
    upto = lambda x: F.floor((x + F.lit(WHOLE // 2)) / F.lit(float(WHOLE)))
    times = summed.select(F.col("doc_id").alias("_mixed_id"), F.col("source").alias("_mixed_source"), (upto(F.col("begin") + F.col("share")) - upto(F.col("begin"))).cast("int").alias("_times"))
    joined = docs.join(times.where("_times > 0"), F.col(id_col).eqNullSafe(F.col("_mixed_id")) & F.col(source_col).eqNullSafe(F.col("_mixed_source")))
    # rows of no words may share an id with others
    joined = joined.where(F.regexp_count(F.col(text_col), F.lit(WORD)) > 0)
    return joined.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_times")))).select(*(joined[c] for c in docs.columns))
