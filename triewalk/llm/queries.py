"""The thin queries over the training-data operators, one opN_<name> each, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load


def word_bpe() -> str:
    """Place of the public tokenizer's file; a parameter of the operators."""
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .langid import language_id

    return language_id(load(spark, sf_dir, "documents"))


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack

    return pack(load(spark, sf_dir, "documents"), word_bpe())


def op3_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .exact_dedup import exact_groups

    return exact_groups(load(spark, sf_dir, "documents"), digest=True)


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .sharding import shard

    return shard(load(spark, sf_dir, "documents"))


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import mix

    return mix(load(spark, sf_dir, "documents"))


def op6_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .licenses import scan_licenses

    return scan_licenses(load(spark, sf_dir, "documents"))


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_files import token_file_digests

    return token_file_digests(load(spark, sf_dir, "documents"), word_bpe())


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .simhash import near_components

    return near_components(load(spark, sf_dir, "documents"))


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality import judge

    return judge(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"))


def op10_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .suffix_dedup import remove_repeats

    return remove_repeats(load(spark, sf_dir, "documents")).drop("kept_text")


def license_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The base columns of op6, which SQL can express."""
    return op6_licenses(spark, sf_dir).select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels")


def quality_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The counts and base rules of op9, which SQL can express."""
    return op9_quality(spark, sf_dir).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")


def mixing_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The columns of op5 that do not depend on the choice of blocks."""
    return op5_mixing(spark, sf_dir).select("doc_id", "size", "source_size", F.round("target", 3).alias("target"))


def mixing_quotas(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks of each source in each shard of the mix."""
    from .mixing import shard_quotas

    return shard_quotas(load(spark, sf_dir, "documents"))


def sharding_cut_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links between rows of equal texts, and how many the shards cut."""
    from .sharding import cut_links, shard

    return cut_links(shard(load(spark, sf_dir, "documents")))


OPERATORS = (op1_language_id, op2_packing, op3_exact_dedup, op4_sharding, op5_mixing, op6_licenses, op7_token_files, op8_simhash, op9_quality, op10_suffix_dedup)
MEASURES = (license_words, quality_counts, mixing_targets, mixing_quotas, sharding_cut_links)
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (*OPERATORS, *MEASURES)}

_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
_SIZES = f"sizes AS (SELECT doc_id, source, len({_WORDS}) AS size FROM documents)"
#: Targets by water filling: the level at which the sources that are below their caps share what is left.
_TARGETS = """
    per AS (SELECT source, sum(size) AS source_size, (ARRAY[5.0, 2.0, 1.0])[((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::INT]::DOUBLE AS weight FROM sizes GROUP BY source),
    level AS (
        SELECT coalesce(max(l), 'inf'::DOUBLE) AS l FROM (
            SELECT a.meets, (sum(b.source_size) - coalesce(sum(b.source_size * 3) FILTER (WHERE b.source_size * 3 / b.weight < a.meets), 0)) / sum(b.weight) FILTER (WHERE b.source_size * 3 / b.weight >= a.meets) AS l
            FROM (SELECT DISTINCT source_size * 3 / weight AS meets FROM per) a, per b GROUP BY a.meets
        ) WHERE l <= meets
    ),
    targets AS (SELECT source, source_size, least(source_size * 3, l * weight)::DOUBLE AS target FROM per, level)
"""

ORACLES: dict[str, str] = {
    "op3_exact_dedup": """
        WITH n AS (SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS text_sha256 FROM documents),
        g AS (SELECT text_sha256, max(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY text_sha256)
        SELECT n.doc_id, g.keep_id, g.group_size, n.doc_id = g.keep_id AS kept, n.text_sha256 FROM n JOIN g USING (text_sha256)
    """,
    "license_words": r"""
        WITH w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
        p AS (SELECT * FROM (VALUES (['under', 'the', 'mit', 'license'], 'mit'), (['apache', 'license', 'version', '2'], 'apache-2'), (['cc', 'by', 'nc'], 'cc-by-nc')) AS t(phrase, label)),
        f AS (SELECT doc_id, label, unnest(list_filter(range(len(w)), lambda i: w[i + 1] = phrase[1] AND list_slice(w, i + 1, i + len(phrase)) = phrase)) AS place FROM w, p),
        g AS (SELECT doc_id, count(*) AS n_base, min(place) AS first_word, max(place) AS last_word, string_agg(DISTINCT label, ',' ORDER BY label) AS base_labels FROM f GROUP BY doc_id)
        SELECT doc_id, len(w) AS n_words, coalesce(n_base, 0) AS n_base, first_word, last_word, coalesce(base_labels, '') AS base_labels FROM w LEFT JOIN g USING (doc_id)
    """,
    "quality_counts": rf"""
        WITH w AS (SELECT doc_id, coalesce(text, '') AS t, {_WORDS} AS w FROM documents),
        lines AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n_dup_lines FROM (SELECT doc_id, unnest(string_split(t, chr(10))) AS line FROM w) WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY doc_id),
        tri AS (SELECT doc_id, unnest(range(len(w) - 2)) AS i, unnest(list_transform(range(len(w) - 2), lambda i: w[i + 1] || ' ' || w[i + 2] || ' ' || w[i + 3])) AS three FROM w WHERE len(w) > 2),
        twice AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, three) AS n FROM tri) WHERE n > 1),
        covered AS (SELECT doc_id, count(DISTINCT i + k) AS n_repeat_words FROM twice, range(3) AS r(k) GROUP BY doc_id)
        SELECT doc_id, len(w) AS n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars, len(regexp_extract_all(t, '[#*$%&|<>]')) AS n_symbols,
            coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words, len(w) < 50 OR 100 * coalesce(n_repeat_words, 0) > 50 * len(w) AS base_failed
        FROM w LEFT JOIN lines USING (doc_id) LEFT JOIN covered USING (doc_id)
    """,
    "mixing_targets": f"""
        WITH {_SIZES}, {_TARGETS}
        SELECT doc_id, size, source_size::BIGINT AS source_size, round(target, 3) AS target FROM sizes JOIN targets ON sizes.source IS NOT DISTINCT FROM targets.source
    """,
    "mixing_quotas": f"""
        WITH {_SIZES}, {_TARGETS},
        b AS (SELECT greatest(ceil(sum(source_size) / 65536), 1) AS block, ceil(sum(source_size) / greatest(ceil(sum(source_size) / 65536), 1)) AS house FROM targets),
        claims AS (SELECT source, target / (2 * award + 1) AS quotient, award FROM targets, b, range(3 * 65536 + 3) AS r(award) WHERE award <= ceil(target / block) AND award < 3 * ceil(source_size / block)),
        won AS (SELECT source, row_number() OVER (ORDER BY quotient DESC, source NULLS LAST, award) AS rank FROM claims QUALIFY rank <= (SELECT house FROM b))
        SELECT source, floor((rank - 1) * 16 / house)::INT AS shard, count(*) AS blocks FROM won, b GROUP BY ALL
    """,
}
