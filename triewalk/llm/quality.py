"""Quality rules with risk-controlled thresholds.

Each text gets counts; each rule turns counts into a severity, which is 1 at the rule's reference cutoff. Cutoffs are chosen per
stratum on labelled rows that no rule was fitted to: from lax to strict, a multiple of the reference cutoffs is accepted as
long as the exact binomial test, at a level shared among all strata (Bonferroni), shows that it rejects no
more than ALPHA of the stratum's good rows. Testing in a fixed order and stopping at the first failure keeps the family-wise
error at DELTA without a further correction for the grid. A stratum with too few labelled rows rejects nothing by these rules.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import lean, materialize, materialize_texts, without_ids

ALPHA, DELTA = 0.025, 0.05
#: Multiples of the reference cutoffs, from lax to strict.
LADDER = (8.0, 6.0, 5.0, 4.0, 3.0, 2.5, 2.0, 1.75, 1.5, 1.25, 1.0)
#: Reference cutoffs: symbols a word character, repeated lines a line, words in repeated windows a word, share of the commonest word.
REFERENCE = {"symbol_share": 0.02, "dup_line_share": 0.45, "repeat_share": 0.3, "top_word_share": 0.3}
#: Strata beyond the largest ones are judged together.
MOST_STRATA = 64

_SPACE = b" \t\n\x0b\x0c\r"
COUNTS = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_lines long, n_top_word long"


def count_text(text: str | None) -> tuple[int, int, int, int, int, int, int]:
    """Words, code points in words, symbols, repeated lines, words in repeated 3-word windows, lines with a word, count of the commonest word."""
    if not text:
        return (0, 0, 0, 0, 0, 0, 0)
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()
    chars = len(text) - (len(raw) - len(raw.translate(None, _SPACE)))
    symbols = len(raw) - len(raw.translate(None, b"#*$%&|<>"))
    lines = [x for x in raw.split(b"\n") if x and not x.isspace()]
    n, top, repeated = len(words), 0, 0
    if n:
        numbers: dict[bytes, int] = {}
        ids = np.fromiter((numbers.setdefault(w, len(numbers)) for w in words), dtype=np.int64, count=n)
        top = int(np.bincount(ids).max())
        if n >= 3:
            # a pair of words gets a rank among the pairs first, so the key of three fits in 64 bits
            pairs = ids[:-1] * len(numbers) + ids[1:]
            if len(numbers) < 2_000_000:
                keys = pairs[:-1] * len(numbers) + ids[2:]
            else:
                keys = np.unique(pairs, return_inverse=True)[1][:-1] * len(numbers) + ids[2:]
            ordered = np.sort(keys)
            twice = ordered[1:][ordered[1:] == ordered[:-1]]
            if len(twice):
                found = np.searchsorted(twice, keys)
                found[found == len(twice)] = 0
                at = twice[found] == keys
                cover = np.zeros(n, dtype=bool)
                for k in range(3):
                    cover[k : k + n - 2] |= at
                repeated = int(cover.sum())
    return (n, chars, symbols, len(lines) - len(set(lines)), repeated, len(lines), top)


def text_counts(docs: DataFrame, keep: list[Column], text_col: str = "text") -> DataFrame:
    """The columns of keep and the counts of the text, for every row."""
    rows = docs.select(*keep, F.col(text_col).alias("_text"))
    kept = rows.schema[:-1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in COUNTS.split(", ")]
        for b in batches:
            counts = [count_text(t.as_py()) for t in b.column(b.num_columns - 1)]
            columns = [pa.array(list(c), pa.int64()) for c in zip(*counts, strict=True)] if counts else [pa.array([], pa.int64())] * len(names)
            yield pa.record_batch([*b.columns[:-1], *columns], names=[*b.schema.names[:-1], *names])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept)
    return rows.mapInArrow(lean(run), f"{schema}, {COUNTS}")


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def severity() -> Column:
    """How many times its reference cutoff the worst rule reaches."""
    share = {
        "symbol_share": F.col("n_symbols") / F.greatest("word_chars", F.lit(1)),
        "dup_line_share": F.col("n_dup_lines") / F.greatest("n_lines", F.lit(1)),
        "repeat_share": F.col("n_repeat_words") / F.greatest("n_words", F.lit(1)),
        "top_word_share": F.col("n_top_word") / F.greatest("n_words", F.lit(1)),
    }
    return F.greatest(*(share[k] / F.lit(v) for k, v in REFERENCE.items()))


def binomial_tail(k: int, n: int, p: float) -> float:
    """P(X <= k) of a binomial with n draws of chance p, exactly (summed in logarithms)."""
    if n == 0:
        return 1.0
    log = [math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(p) + (n - i) * math.log1p(-p) for i in range(k + 1)]
    top = max(log)
    return min(1.0, math.exp(top) * math.fsum(math.exp(x - top) for x in log))


def certified_level(good: int, rejected: list[int], strata: int, alpha: float = ALPHA, delta: float = DELTA) -> float | None:
    """The strictest step of LADDER that may be used: rejected[i] of the good rows fall to step i; None if not even the first one is safe."""
    level = None
    for step, k in zip(LADDER, rejected, strict=True):
        if binomial_tail(k, good, alpha) > delta / strata:
            break
        level = step
    return level


def calibrate(scored: DataFrame, labels: DataFrame, alpha: float = ALPHA, delta: float = DELTA) -> list[tuple[str | None, int, float | None]]:
    """(stratum, good labelled rows, level) of each stratum, from all labelled rows that pass the base rules.

    Strata beyond the MOST_STRATA with most labelled rows are one further stratum, named None and given last if there are any.
    scored: doc_id, stratum, severity, base_failed. labels: doc_id, quality (1 is good; null rows and other values are not used).
    """
    good = labels.where("quality = 1").select(F.col("doc_id").alias("_label_id")).distinct()
    held = scored.where("not base_failed").join(good, F.col("doc_id") == F.col("_label_id"))
    falls = [F.sum((F.col("severity") > step).cast("long")).alias(f"r{i}") for i, step in enumerate(LADDER)]
    per = materialize(held.groupBy("stratum").agg(F.count(F.lit(1)).alias("n"), *falls), "quality-strata")
    rows = per.orderBy(F.col("n").desc(), "stratum").limit(MOST_STRATA).collect()
    if len(rows) == MOST_STRATA:
        rest = per.where(~F.col("stratum").isin([r["stratum"] for r in rows])).agg(*(F.sum(c).alias(c) for c in per.columns if c != "stratum"))
        rows += rest.where("n > 0").withColumn("stratum", F.lit(None).cast("string")).collect()
    return [(r["stratum"], r["n"], certified_level(r["n"], [r[f"r{i}"] for i in range(len(LADDER))], len(rows), alpha, delta)) for r in rows]


def judge(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum_col: str = "lang") -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, severity, level for every row of docs.

    kept: false if a base rule fails or the severity is over the stratum's certified level. A null text has no words and fails. A null
    stratum is one of its own. Rows that repeat an id count once each. With no labels nothing but the base rules rejects. Whole
    texts are counted, however long; other columns are not read. An empty table gives an empty result.
    """
    counts = text_counts(docs, [F.col(id_col).alias("doc_id"), F.coalesce(F.col(stratum_col).cast("string"), F.lit("")).alias("stratum")], text_col)
    scored = materialize_texts(counts.withColumn("base_failed", base_failed()).withColumn("severity", severity()), "quality-counts")
    levels = calibrate(scored, labels)
    # the stratum of all others goes to every row outside the named ones
    level = F.lit(next((step for name, _, step in levels if name is None), None)).cast("double")
    for name, _, step in levels:
        if name is not None:
            level = F.when(F.col("stratum") == name, F.lit(step).cast("double")).otherwise(level)
    out = scored.withColumn("level", level)
    over = F.coalesce(F.col("severity") > F.col("level"), F.lit(False))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", (~F.col("base_failed") & ~over).alias("kept"), "severity", "level")


def keep_good(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum_col: str = "lang") -> DataFrame:
    """The rows of docs that judge keeps, all columns as they are. A repeated id stays only if all its rows are kept."""
    gone = judge(docs, labels, id_col, text_col, stratum_col).where("not kept").select("doc_id").distinct()
    return without_ids(docs, materialize(gone, "quality-gone"), id_col)
