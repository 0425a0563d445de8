"""Sharding by balanced label propagation: documents of equal text are linked and move, in a few rounds of joins, towards
the shard where most of their group lies, as far as the shard's quota allows; then counts are made equal to one row.

A group of equal texts is a node to which its rows are tied (a star, never all pairs). Groups larger than an eighth of a
quota are few; they are placed first, the largest first, each whole where a shard still has room for it. Only one that
no shard can hold is cut, by row, over as few shards as have the room.
"""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize
from .ranks import running_start

SHARDS = 16
ROUNDS = 3
BUCKETS = 1024
#: A shard may stand this far over its quota between rounds.
SLACK = 1.05


def _by_case(col: str, values: dict[int, float], other: float):
    """A lookup in at most SHARDS values, as an expression."""
    out = F.lit(other)
    for k, v in values.items():
        out = F.when(F.col(col) == k, F.lit(v)).otherwise(out)
    return out


def _counts(df: DataFrame, by: str) -> dict[int, int]:
    """At most SHARDS rows."""
    return {r[0]: r[1] for r in df.groupBy(by).agg(F.count(F.lit(1))).collect()}


def place_large(sizes: dict[int, int], shards: int, n: int) -> dict[int, list[tuple[int, int]]]:
    """(shard, rows) of each group: the tightest shard that holds it, or else the roomiest ones in turn."""
    room = {s: n // shards + (s < n % shards) for s in range(shards)}
    placed = {}
    for key, left in sorted(sizes.items(), key=lambda x: (-x[1], x[0])):
        placed[key] = []
        while left:
            fits = [s for s in room if room[s] >= left]
            s = min(fits, key=lambda s: (room[s], s)) if fits else max(room, key=lambda s: (room[s], -s))
            take = min(left, room[s])
            placed[key].append((s, take))
            room[s] -= take
            left -= take
    return placed


def propagate(rows: DataFrame, shards: int, rounds: int, n: int) -> DataFrame:
    """rows (row_no, part, linked, pinned) with a label: rows with a pinned one have that; the others start at random and moves whole parts towards their majority shard.

    A part is accepted by its new shard with the probability that the shard's room allows, drawn from the part's own
    hash, so a rerun decides alike.
    """
    quota = n / shards
    pinned = rows.where("pinned is not null").withColumn("label", F.col("pinned"))
    at = rows.where("pinned is null").withColumn("label", F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(shards)).cast("int"))
    lone = at.where("not linked")
    # one row a part and label: the rows of a part that share a label move together
    tally = materialize(at.where("linked").groupBy("part", "label").agg(F.count(F.lit(1)).alias("n")), "shard-tally")
    lone_at, pinned_at = _counts(lone, "label"), _counts(pinned, "label")
    for turn in range(rounds):
        best = tally.groupBy("part").agg(F.max(F.struct("n", F.xxhash64("part", "label").alias("tie"), "label")).getField("label").alias("to"), F.sum("n").alias("size"))
        moved = tally.join(best, "part")
        held = {r[0]: r[1] for r in tally.groupBy("label").agg(F.sum("n")).collect()}
        leaving = {r[0]: r[1] for r in moved.where("label != to").groupBy("label").agg(F.sum("n")).collect()}
        coming = {r[0]: r[1] for r in moved.where("label != to").groupBy("to").agg(F.sum("n")).collect()}
        if not coming:
            break
        accept = {}
        for s in range(shards):
            room = quota * SLACK - lone_at.get(s, 0) * (0.0 if turn else 0.5) - pinned_at.get(s, 0) - held.get(s, 0) + leaving.get(s, 0)
            accept[s] = max(0.0, min(1.0, room / coming[s])) if coming.get(s) else 1.0
        draw = F.pmod(F.xxhash64("part", F.lit(turn)), F.lit(1 << 30)) / float(1 << 30)
        ok = draw < _by_case("to", accept, 1.0)
        tally = materialize(moved.withColumn("label", F.when(ok, F.col("to")).otherwise(F.col("label"))).groupBy("part", "label").agg(F.sum("n").alias("n")), "shard-tally")
    # a part that was refused stays split over several labels; its rows are dealt by their own hash among those
    ends = tally.groupBy("part").agg(F.sort_array(F.collect_set("label")).alias("labels"))
    ends = materialize(ends, "shard-ends")
    pick = F.element_at("labels", (F.pmod(F.xxhash64("doc_id", F.lit(2)), F.size("labels").cast("long")) + 1).cast("int"))
    columns = ["row_no", "doc_id", "size", "text_crc32", "part", "linked", "pinned"]
    moved = at.where("linked").drop("label").join(ends, "part").select(*columns, pick.alias("label"))
    return lone.select(*columns, "label").unionByName(moved).unionByName(pinned.select(*columns, "label"))


def even_out(placed: DataFrame, n: int, shards: int) -> DataFrame:
    """Moves as few rows as needed, rows without links first, so that counts differ by one at most; adds shard."""
    have = _counts(placed, "label")
    quota = {s: n // shards + (s < n % shards) for s in range(shards)}
    over = {s: max(0, have.get(s, 0) - quota[s]) for s in range(shards)}
    under = {s: max(0, quota[s] - have.get(s, 0)) for s in range(shards)}
    mixed = F.xxhash64("row_no", F.lit(3))
    # lone rows stand in the lower third of the buckets, linked ones, by part, in the next, those of large groups in the last
    spot = F.when(F.col("pinned").isNotNull(), F.pmod(mixed, F.lit(BUCKETS)) + 2 * BUCKETS).when(F.col("linked"), F.pmod(F.xxhash64("part"), F.lit(BUCKETS)) + BUCKETS).otherwise(F.pmod(mixed, F.lit(BUCKETS)))
    ranked = running_start(placed, ["label"], spot, [F.col("part"), mixed, F.col("row_no")], F.lit(1), 3 * BUCKETS, "rank", shards)
    base, first = {}, 0
    for s in range(shards):
        base[s], first = first, first + over[s]
    pool = F.col("rank") + _by_case("label", base, 0)
    goal, upto = F.lit(None).cast("int"), first
    for s in reversed(range(shards)):
        goal = F.when((pool >= upto - under[s]) & (pool < upto), F.lit(s)).otherwise(goal)
        upto -= under[s]
    return ranked.withColumn("shard", F.when(F.col("rank") < _by_case("label", over, 0), goal).otherwise(F.col("label")).cast("int"))


def shard(docs: DataFrame, shards: int = SHARDS, rounds: int = ROUNDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard, linked, cut for every row of docs, by the law `rows`.

    Size: the text's UTF-8 bytes plus 1 (null: 1). A null text is linked with empty ones. linked: whether others have the row's
    text; cut: whether it stands outside the shard that holds most of them, so that its link is an edge that was cut. A null or
    repeated id makes a row of its own. An empty table gives an empty result; other columns are not read.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(
        F.col(id_col).alias("doc_id"),
        F.monotonically_increasing_id().alias("row_no"),
        (F.octet_length(text).cast("long") + 1).alias("size"),
        F.crc32(text).alias("text_crc32"),
        F.xxhash64(text, F.crc32(text), F.octet_length(text)).alias("text_key"),
    )
    rows = materialize(rows, "shard-rows")
    n = rows.count()
    groups = materialize(rows.groupBy("text_key").agg(F.count(F.lit(1)).alias("copies")).where("copies > 1").select(F.col("text_key").alias("k"), "copies"), "shard-groups")
    # less than eight such groups a shard, however many rows there are
    large = max(1, n // (shards * 8))
    homes = place_large({r["k"]: r["copies"] for r in groups.where(F.col("copies") > large).collect()}, shards, n)
    pieces = [(k, s, upto - rows_here, upto) for k, home in homes.items() for (s, rows_here), upto in zip(home, accumulate(x for _, x in home), strict=True)]
    spread = docs.sparkSession.createDataFrame([(k, s, a / home, z / home) for k, s, a, z in pieces for home in [sum(x for _, x in homes[k])]], "hk long, pinned int, lo double, hi double")
    joined = rows.join(groups, F.col("text_key") == F.col("k"), "left")
    draw = F.pmod(F.xxhash64("row_no"), F.lit(1 << 30)) / float(1 << 30)
    joined = joined.join(F.broadcast(spread), (F.col("text_key") == F.col("hk")) & (draw >= F.col("lo")) & (draw < F.col("hi")), "left")
    parts = joined.select("row_no", "doc_id", "size", "text_crc32", F.xxhash64("text_key").alias("part"), F.col("copies").isNotNull().alias("linked"), "pinned")
    placed = materialize(propagate(materialize(parts, "shard-parts"), shards, rounds, n), "shard-placed")
    even = materialize(even_out(placed, n, shards), "shard-even")
    mixed = F.xxhash64("row_no", F.lit(4))
    spread_out = even.where("linked").groupBy("part", "shard").agg(F.count(F.lit(1)).alias("n")).groupBy("part").agg(F.max(F.struct("n", -F.col("shard"))).alias("top"), F.count(F.lit(1)).alias("shards"))
    homes = materialize(spread_out.where("shards > 1").select(F.col("part").alias("_part"), (-F.col("top.col2")).alias("_home")), "shard-homes")
    even = even.join(homes, F.col("linked") & (F.col("part") == F.col("_part")), "left")
    slotted = running_start(even, ["shard"], F.pmod(mixed, F.lit(BUCKETS)), [mixed, F.col("row_no")], F.lit(1), BUCKETS, "slot", shards)
    cut_off = F.coalesce(F.col("shard") != F.col("_home"), F.lit(False))
    return slotted.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", F.col("slot").cast("long"), F.lit(None).cast("int").alias("grown_shard"), "linked", cut_off.alias("cut"))


def cut_links(placed: DataFrame) -> DataFrame:
    """One row: links (a row to its text's group, for texts of several rows) and how many of them the shards cut."""
    return placed.where("linked").agg(F.count(F.lit(1)).alias("links"), F.coalesce(F.sum(F.col("cut").cast("long")), F.lit(0)).alias("cut"))
