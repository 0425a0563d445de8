"""The pipeline's stages on the smallest documents and on an awkward table, each against a brute-force version of its decisions."""

from collections import defaultdict

import pytest

import corpus_pipeline
from triewalk.llm import simhash
from triewalk.llm.common import materialize
from triewalk.llm.queries import word_bpe
from triewalk.llm.tokens import WordEncoder

from .test_operators import LONG, lower

SMALL = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    columns, n = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = materialize(stage(spark, docs, SMALL), name)
        assert docs.columns == columns
        if name != "mixing":
            assert 0 < docs.count() <= n
            n = docs.count()
    assert corpus_pipeline.STAGES[-1][1](spark, docs, SMALL).groupBy("sequence_id").sum("length").where("`sum(length)` > 2048").count() == 0


def test_kept_texts_differ(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    kept = corpus_pipeline.exact_dedup(spark, docs, SMALL)
    assert kept.count() == kept.select("text").distinct().count()


def test_empty_documents(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").limit(0)
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, SMALL)
        assert out.count() == 0, name


SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, kept boolean, root long, id long"


@pytest.fixture(scope="module")
def awkward(spark):
    """Nulls in every column, empty and long texts, repeated rows, a repeated id and columns of names that the stages use inside."""
    words = [f"w{i * 7919 % 997}" for i in range(120)]
    text = " ".join(words)
    near = " ".join(["other", *words[1:]])
    texts = [text, text.upper(), near, None, "", " \n", LONG, "Some short text.", text, " ".join(f"v{i}" for i in range(90)), " ".join(f"v{i}" for i in range(90, 190))]
    rows = [(i, t, (None, "en")[i % 2], (None, "s", "t")[i % 3], None, 1, True, 2, 3) for i, t in enumerate(texts)]
    rows += [rows[0], (9, " ".join(f"u{i}" for i in range(70)), None, "s", 1, None, None, None, None), (None, " ".join(f"n{i}" for i in range(70)), None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA)


def exact_by_hand(rows):
    keep = {}
    for r in rows:
        key = lower(r["text"])
        if key not in keep or (r["doc_id"] is not None and (keep[key] is None or r["doc_id"] > keep[key])):
            keep[key] = r["doc_id"]
    return sorted(keep.values(), key=repr)


def near_by_hand(rows):
    """Ids of rows that stay: a null id or no link, or the least id of the component. Rows of one id are one document."""
    sets = defaultdict(list)
    for r in rows:
        if r["doc_id"] is not None:
            sets[r["doc_id"]].append(set(simhash.shingle_hashes(r["text"], simhash.SHINGLE).tolist()))
    ids = sorted(sets)
    forest = simhash.Forest(len(ids))
    for i, a in enumerate(ids):
        for j in range(i):
            if any(x & y and len(x & y) >= simhash.SIMILARITY * len(x | y) for x in sets[a] for y in sets[ids[j]]):
                forest.join(i, j)
    stay = {a for i, a in enumerate(ids) if forest.root(i) == i}
    return sorted((r["doc_id"] for r in rows if r["doc_id"] is None or r["doc_id"] in stay), key=repr)


@pytest.mark.parametrize("which", ["small", "awkward"])
def test_stages_by_brute_force(spark, awkward, which):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet") if which == "small" else awkward
    columns = docs.columns
    good = materialize(corpus_pipeline.quality(spark, docs, SMALL), "good")
    assert 0 < good.count() < docs.count()
    # whatever quality would reject goes through the next stages as well here
    exact = materialize(corpus_pipeline.exact_dedup(spark, docs, SMALL), "exact")
    assert sorted((r["doc_id"] for r in exact.collect()), key=repr) == exact_by_hand(docs.collect())
    near = materialize(corpus_pipeline.near_dedup(spark, exact, SMALL), "near")
    assert sorted((r["doc_id"] for r in near.collect()), key=repr) == near_by_hand(exact.collect())
    assert near.count() < exact.count()
    mixed = materialize(corpus_pipeline.mixing(spark, near, SMALL), "mixed")
    assert good.columns == exact.columns == near.columns == mixed.columns == columns
    e = WordEncoder(word_bpe())
    pieces = corpus_pipeline.packing(spark, mixed, SMALL).collect()
    assert sum(r["length"] for r in pieces) == sum(len(e.encode(r["text"])) // 4 for r in mixed.collect())
