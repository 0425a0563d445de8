"""Exact dedup by progressive refinement: length, then a hash of the prefix, then a hash of the whole text.

The first scan keeps a length and a hash of the prefix for each row, no text. Lengths that occur once settle their rows; of the
others' rows the prefix hashes are compared, and the (length, prefix) groups of more than one row go into a bitmap of a
fixed size, which is broadcast. In the second scan only texts whose bit is set are hashed in full. A row whose bit is set
by chance costs one hash and changes no result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, bitmap_of, marked, materialize

PREFIX_CHARS = 256


def _length(text: Column) -> Column:
    return F.octet_length(text)


def _prefix(text: Column) -> Column:
    return F.xxhash64(ascii_lower(F.substring(text, 1, PREFIX_CHARS)))


def candidates(texts: DataFrame) -> DataFrame:
    """Bitmap of the (length, prefix) keys that more than one row of texts (raw) has: by length first, then by prefix among the lengths left."""
    keys = materialize(texts.select(_length(F.col("raw")).alias("length"), _prefix(F.col("raw")).alias("prefix")), "dedup-keys")
    lengths = keys.groupBy(F.col("length").alias("_l")).agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("_l")
    left = keys.join(materialize(lengths, "dedup-lengths"), F.col("length") == F.col("_l"), "left_semi")
    again = left.groupBy("length", "prefix").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    return bitmap_of(again, F.xxhash64("length", "prefix"), "dedup-bitmap")


def _survivors(texts: DataFrame, bitmap: DataFrame) -> DataFrame:
    """texts (raw, ...) with `maybe`: whether the row's length and prefix may have others."""
    return marked(texts, bitmap, F.xxhash64(_length(F.col("raw")), _prefix(F.col("raw"))), "maybe")


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", digest: bool = False, bitmap: DataFrame | None = None) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 for every row of docs. The hash of the normalised text is null for rows that
    the refinement settles without it, unless digest asks for all. bitmap: of candidates(), if there already.

    Texts are equal when the same after lower-casing A-Z; a null text counts as empty, so nulls and empty texts are one
    group. Of a group the row with the largest id stays (a null id is below all others); of rows that repeat both text
    and id exactly one is kept. Other columns of docs are not read. Whole texts count, however long. An empty table gives an empty result.
    """
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("raw"))
    tested = _survivors(rows, candidates(rows) if bitmap is None else bitmap)
    whole = F.sha2(ascii_lower(F.col("raw")), 256)
    narrow = tested.select(
        "doc_id",
        F.monotonically_increasing_id().alias("row_no"),
        "maybe",
        (whole if digest else F.when(F.col("maybe"), whole)).alias("text_sha256"),
    )
    narrow = materialize(narrow, "dedup-hashes")
    groups = (
        narrow.where("maybe")
        .groupBy("text_sha256")
        .agg(F.max(F.struct("doc_id", "row_no")).alias("top"), F.count(F.lit(1)).alias("n"))
        .where("n > 1")
        .select(F.col("text_sha256").alias("key"), F.col("top.doc_id").alias("top_id"), F.col("top.row_no").alias("top_row"), "n")
    )
    groups = materialize(groups, "dedup-groups")
    # Both sides are plain scans under one exchange each, so adaptive execution can split the partition of a hot text.
    key = F.coalesce(F.when(F.col("maybe"), F.col("text_sha256")), F.concat(F.lit("-"), F.col("row_no").cast("string")))
    joined = narrow.withColumn("key", key).join(groups, "key", "left")
    out = joined.select(
        "doc_id",
        F.when(F.col("n").isNull(), F.col("doc_id")).otherwise(F.col("top_id")).alias("keep_id"),
        F.coalesce("n", F.lit(1)).cast("long").alias("group_size"),
        F.coalesce(F.col("top_row") == F.col("row_no"), F.lit(True)).alias("kept"),
        "text_sha256",
    )
    return out


def drop_exact_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs that exact_groups keeps, with all their columns; of rows that repeat text and id, one stays.

    Only texts that length and prefix leave are hashed in full. Rows that go are known by id and full hash: what a bitmap of these marks is
    shuffled by both, so a text of many copies spreads over all tasks; all other rows stay where they are. An empty table gives an empty result.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    bitmap = candidates(docs.select(text.alias("raw")))
    verdict = materialize(exact_groups(docs, id_col, text_col, bitmap=bitmap).where("not kept").select(F.col("doc_id").alias("_id"), F.col("keep_id"), F.col("text_sha256").alias("_hash")), "dedup-verdict")
    gone = verdict.where("not (_id <=> keep_id)").select("_id", "_hash").distinct()
    # rows that repeat the id of the one that stays
    twice = verdict.where("_id <=> keep_id").select("_id", "_hash").distinct()
    key = lambda i, h: F.xxhash64(F.coalesce(F.col(i).cast("long"), F.lit(-1)), F.col(h))
    tested = marked(docs, bitmap, F.xxhash64(_length(text), _prefix(text)), "_survives")
    keyed = tested.withColumn("_sha", F.when(F.col("_survives"), F.sha2(ascii_lower(text), 256)))
    flagged = marked(keyed, bitmap_of(verdict, key("_id", "_hash"), "copies-bitmap"), key(id_col, "_sha"), "_maybe").withColumn("_maybe", F.col("_maybe") & F.col("_survives"))
    alone = flagged.where("not _maybe").select(*docs.columns)
    same = F.col(id_col).eqNullSafe(F.col("_id")) & (F.col("_sha") == F.col("_hash"))
    left = flagged.where("_maybe").select(*docs.columns, "_sha").join(gone, same, "left_anti")
    if not twice.limit(1).count():
        return alone.unionByName(left.select(*docs.columns))
    once = left.join(twice, same, "left_semi").dropDuplicates([id_col, "_sha"])
    return alone.unionByName(left.join(twice, same, "left_anti").select(*docs.columns)).unionByName(once.select(*docs.columns))
