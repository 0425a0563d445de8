"""The training-data operators on small awkward tables, against brute force, and the named queries against SQL or brute force."""

import hashlib
import json
import math
import random
import re
import struct
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from triewalk.llm import golay, langid, licenses, packing, quality, simhash, suffix_dedup
from triewalk.llm.anchors import PART, runs
from triewalk.llm.components import components
from triewalk.llm.exact_dedup import drop_exact_copies, exact_groups
from triewalk.llm.mixing import mix, repeat_mixed, shard_quotas
from triewalk.llm.queries import ORACLES, QUERIES, word_bpe
from triewalk.llm.sharding import cut_links, shard
from triewalk.llm.suffix_sort import common_prefixes, suffix_array
from triewalk.llm.token_files import ShardReader, token_file_digests, write_token_files
from triewalk.llm.tokens import WordEncoder, same_rules

SMALL = "/root/testdata/sf0.001"
# extra columns carry names that the operators use inside
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, kept boolean, label string, bucket int, key string, id long"
LONG = "word other thing " * 4000
TEXTS = ["Same Text", "same text", None, "", " \n\t ", "ßÉ É", "ÉÉ", LONG, "a b c d e f", "Under the MIT License.", "日本語 テキスト", "x" * 450, "12 34 !!", "same text"]


@pytest.fixture(scope="module")
def awkward(spark):
    rows = [(i, t, (None, "en", "fr")[i % 3], (None, "s1", "s2", "s0")[i % 4], None, 1, True, "x", 3, "k", 9) for i, t in enumerate(TEXTS)]
    rows += [rows[1], (None, "null id", None, None, None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def no_labels(spark):
    return spark.createDataFrame([], "doc_id long, quality int, toxic int")


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SMALL}/documents.parquet")


def got(df):
    return sorted((tuple(r) for r in df.collect()), key=repr)


def lower(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


def apply_all(df, labels):
    tok = word_bpe()
    return {
        "lang": langid.language_id(df),
        "pack": packing.pack(df, tok),
        "exact": exact_groups(df, digest=True),
        "shard": shard(df),
        "mix": mix(df),
        "license": licenses.scan_licenses(df),
        "files": token_file_digests(df, tok),
        "near": simhash.near_components(df),
        "quality": quality.judge(df, labels),
        "suffix": suffix_dedup.remove_repeats(df),
        "drop_exact": drop_exact_copies(df),
        "repeat": repeat_mixed(df),
        "keep": quality.keep_good(df, labels),
        "drop_near": simhash.drop_near_copies(df),
    }


def test_empty_tables(empty, no_labels):
    for name, out in apply_all(empty, no_labels).items():
        assert out.count() == 0, name


def test_awkward_rows(awkward, no_labels):
    n = awkward.count()
    out = apply_all(awkward, no_labels)
    for name in ("lang", "exact", "shard", "mix", "license", "files", "near", "quality", "suffix"):
        assert out[name].count() == n, name
    for name in ("drop_exact", "repeat", "keep", "drop_near"):
        assert out[name].columns == awkward.columns, name
    assert {r["lang_pred"] for r in out["lang"].where("doc_id in (2, 3, 4, 12)").collect()} == {"und"}


def test_exact(awkward):
    rows = [tuple(r)[:2] for r in awkward.select("doc_id", "text").collect()]
    groups = defaultdict(list)
    for i, t in rows:
        groups[hashlib.sha256(lower(t).encode()).hexdigest()].append(i)
    for r in exact_groups(awkward, digest=True).collect():
        g = groups[r["text_sha256"]]
        assert r["doc_id"] in g and r["group_size"] == len(g)
        assert r["keep_id"] == max((x for x in g if x is not None), default=None)
    kept = Counter(r["text_sha256"] for r in exact_groups(awkward, digest=True).where("kept").collect())
    assert set(kept.values()) == {1} and len(kept) == len(groups)
    assert drop_exact_copies(awkward).count() == len(groups)
    # the refinement alone: only rows that share length and prefix with others are hashed in full
    hashed = {r["doc_id"]: r["text_sha256"] for r in exact_groups(awkward).where("text_sha256 is not null").collect()}
    whole = {r["doc_id"]: tuple(r) for r in exact_groups(awkward, digest=True).drop("text_sha256").collect()}
    assert whole == {r["doc_id"]: tuple(r) for r in exact_groups(awkward).drop("text_sha256").collect()}
    assert {0, 1, 2, 3, 13} <= set(hashed) and not {7, 9, 10} & set(hashed)


def test_mix(spark, docs, awkward):
    for df in (docs, awkward):
        by = defaultdict(lambda: [0, 0.0, 0, 0])
        for r in mix(df).join(df.select("doc_id", "source").distinct(), "doc_id").collect():
            assert 0 <= r["taken"] <= 3 * r["size"]
            x = by[r["source"]]
            x[0] += r["size"]
            x[1], x[2], x[3] = r["target"], r["source_size"], x[3] + r["taken"]
        if df is docs:
            total = sum(x[0] for x in by.values())
            assert sum(x[1] for x in by.values()) == pytest.approx(total)
            # water filling by hand
            names = sorted(by, key=lambda s: (s is None, s))
            weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
            target, full, left = {}, set(), total
            while True:
                free = [s for s in names if s not in full]
                w = sum(weight[s] for s in free)
                target |= {s: left * weight[s] / w for s in free}
                over = [s for s in free if target[s] > 3 * by[s][0]]
                if not over:
                    break
                for s in over:
                    target[s] = 3 * by[s][0]
                    left -= target[s]
                    full.add(s)
            for s in names:
                assert by[s][1] == pytest.approx(target[s]) and by[s][0] == by[s][2]
                assert abs(by[s][3] - by[s][1]) <= max(3, 0.01 * by[s][1])
    assert got(mix(docs)) == got(mix(docs.repartition(5)))


def test_shard_quotas(docs, empty):
    by = defaultdict(int)
    for r in shard_quotas(docs).collect():
        assert r["blocks"] > 0
        by[r["shard"]] += r["blocks"]
    assert set(by) == set(range(16)) and max(by.values()) - min(by.values()) <= 1
    assert shard_quotas(empty).count() == 0


def test_repeat_mixed_meets_targets(spark, docs):
    # documents of many blocks each: a block of these tables is a word or so
    rng = random.Random(6)
    made = spark.createDataFrame([(i, "w " * int(20 + rng.paretovariate(1.1) * 40), f"s{i % 6}") for i in range(3000)], "doc_id long, text string, source string")
    for df in (docs, made):
        size = {r["doc_id"]: len((r["text"] or "").encode().split()) for r in df.collect()}
        source = {r["doc_id"]: r["source"] for r in df.collect()}
        target = {source[r["doc_id"]]: r["target"] for r in mix(df).collect()}
        kept, longest = Counter(), Counter()
        for i, s in source.items():
            longest[s] = max(longest[s], size[i])
        for r in repeat_mixed(df).select("doc_id", "source").collect():
            kept[r["source"]] += size[r["doc_id"]]
        for s, t in target.items():
            assert abs(kept[s] - t) <= 0.01 * t + longest[s], (s, kept[s], t)


def test_shard(docs, awkward):
    for df in (docs, awkward):
        rows = shard(df).collect()
        slots = defaultdict(list)
        for r in rows:
            slots[r["shard"]].append(r["slot"])
        assert all(sorted(s) == list(range(len(s))) for s in slots.values())
        counts = [len(slots.get(k, [])) for k in range(16)]
        assert max(counts) - min(counts) <= 1 and sum(counts) == len(rows)
    texts = {r["doc_id"]: (r["text"] or "") for r in docs.collect()}
    homes = defaultdict(set)
    for r in shard(docs).collect():
        t = texts[r["doc_id"]].encode()
        assert (r["size"], r["text_crc32"], r["law"]) == (len(t) + 1, zlib.crc32(t), "rows")
        homes[t].add(r["shard"])
    n_groups = [t for t, c in Counter(texts.values()).items() if c > 1]
    assert sum(len(homes[t.encode()]) == 1 for t in n_groups) >= 0.9 * len(n_groups)


def test_shard_keeps_large_groups(spark):
    # a quota is 400 rows; the last group exceeds it and needs two shards
    sizes = [390, 300, 210, 120, 60, 500]
    rows = [f"group {g}" for g, n in enumerate(sizes) for _ in range(n)]
    rows += [f"lone {i}" for i in range(6400 - len(rows))]
    df = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")
    homes = defaultdict(Counter)
    for r in shard(df).collect():
        homes[rows[r["doc_id"]]][r["shard"]] += 1
    for g, n in enumerate(sizes):
        assert len(homes[f"group {g}"]) <= (1 if n <= 400 else 3), (n, homes[f"group {g}"])
        assert max(homes[f"group {g}"].values()) >= min(n, 360)
    placed = shard(df)
    outside = sum(sum(h.values()) - max(h.values()) for g, h in homes.items() if g.startswith("group"))
    assert tuple(cut_links(placed).first()) == (sum(sizes), outside) and placed.where("cut and not linked").count() == 0


@pytest.mark.parametrize("n", [160, 6400])
def test_shard_is_alike_at_all_sizes(spark, n):
    """Groups of a tenth and a fortieth of a quota and more stay whole, however many rows there are."""
    quota = n // 16
    sizes = [max(2, quota // k) for k in (1, 2, 3, 10, 40)]
    rows = [f"group {g}" for g, m in enumerate(sizes) for _ in range(m)]
    rows += [f"lone {i}" for i in range(n - len(rows))]
    df = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")
    assert tuple(cut_links(shard(df)).first()) == (sum(sizes), 0)


def test_tokens_and_files(spark, awkward, docs, tmp_path):
    e = WordEncoder(word_bpe())
    extra = ["it's I'LL 'S've", "a\x0bb\x1cc\x85d", "<|endoftext|> x", "ΣΑΣ", "İ ẞ ß", "²³¼ 1.5%", "é", "__a__", "“q”…", "\x00a"]
    for t in [*TEXTS, *extra, *(r["text"] for r in docs.collect())]:
        want = [*e.tokenizer.encode(t or "", add_special_tokens=False).ids, 1]
        assert e.encode(t) == struct.pack(f"<{len(want)}I", *want), repr(t)[:60]
    rows = token_file_digests(awkward.where("doc_id is not null"), word_bpe(), 3).orderBy("doc_id").collect()
    start = 0
    for r in rows:
        ids = e.encode(TEXTS[r["doc_id"]])
        assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (start, len(ids) // 4, zlib.crc32(ids))
        start += len(ids) // 4
    # several batches in a shard
    many = spark.range(300).selectExpr("id as doc_id", "repeat(concat('w', id, ' '), 1000 + id) as text")
    start = 0
    for r, m in zip(token_file_digests(many, word_bpe(), 1).orderBy("doc_id").collect(), many.orderBy("doc_id").collect(), strict=True):
        ids = e.encode(m["text"])
        assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (start, len(ids) // 4, zlib.crc32(ids))
        start += len(ids) // 4
    assert start > 2 * 256 * 1024
    folder = f"file://{tmp_path}/shards"
    manifest = write_token_files(docs, folder, word_bpe(), 2)
    assert sum(d for _, d, _ in manifest) == docs.count()
    reader = ShardReader(folder, manifest[0][0])
    doc_id, a, n = next(reader.documents())
    assert np.array_equal(np.concatenate(reader.span(a, n))[:1024], reader.row(0)[: min(n, 1024)])


def test_tokens_equal_the_library():
    """All code points below U+0250 singly and in pairs, and random strings of them."""
    e = WordEncoder(word_bpe())
    low = [chr(c) for c in range(0x250)]
    rng = random.Random(1)
    mixed = ["".join(rng.choice(low) if rng.random() < 0.5 else rng.choice("abc 's'tZ9\n") for _ in range(rng.randrange(1, 30))) for _ in range(100_000)]
    named = ["Əliyev", "AZƏRBAYCAN", "ƁARNA Ɗan"]
    for texts in (low, named, mixed, *([a + b for b in low] for a in low)):
        for text, want in zip(texts, e.tokenizer.encode_batch(texts, add_special_tokens=False), strict=True):
            assert e.encode(text) == struct.pack(f"<{len(want.ids) + 1}I", *want.ids, 1), repr(text)


def test_other_tokenizer_files_go_through_the_library(tmp_path):
    with open(word_bpe(), encoding="utf-8") as f:
        stated = json.load(f)
    stated["normalizer"] = {"type": "NFC"}
    path = tmp_path / "other.json"
    path.write_text(json.dumps(stated), encoding="utf-8")
    assert same_rules(word_bpe()) and not same_rules(str(path))
    e = WordEncoder(str(path))
    want = e.tokenizer.encode("Some Words ABC", add_special_tokens=False).ids
    assert e.encode("Some Words ABC") == struct.pack(f"<{len(want) + 1}I", *want, 1) != WordEncoder(word_bpe()).encode("Some Words ABC")


def test_differencing():
    assert sorted(np.bincount(packing.difference(np.array([8, 7, 6, 5, 4]), 2), weights=[8, 7, 6, 5, 4]).tolist()) == [14.0, 16.0]
    rng = np.random.default_rng(2)
    for n, k in ((1, 3), (5, 1), (40, 7), (500, 60)):
        sizes = np.sort(rng.integers(1, 300, n))[::-1]
        w = packing.difference(sizes, k)
        assert w.min() >= 0 and w.max() < k
        loads = np.bincount(w, weights=sizes, minlength=k)
        assert loads.sum() == sizes.sum() and (n < 3 * k or loads.max() - loads.min() <= sizes.max())
        assert np.bincount(packing.pack_sizes(sizes, 512), weights=sizes).max() <= 512
    assert packing.cut(2048) == [(0, 2048)] and packing.cut(1) == [(0, 1)]
    assert sum(m for _, m in packing.cut(5000)) == 5000


def test_pack(docs, awkward):
    e = WordEncoder(word_bpe())
    for df in (docs, awkward.where("doc_id is not null").dropDuplicates(["doc_id"])):
        ids = {r["doc_id"]: e.encode(r["text"]) for r in df.collect()}
        pieces, sequences = defaultdict(list), defaultdict(list)
        for r in packing.pack(df, word_bpe()).collect():
            pieces[r["doc_id"]].append((r["start"], r["length"]))
            sequences[r["sequence_id"]].append((r["offset"], r["length"]))
            x = ids[r["doc_id"]]
            assert r["doc_tokens"] == len(x) // 4 and r["ids_crc32"] == zlib.crc32(x[4 * r["start"] : 4 * (r["start"] + r["length"])])
        for spans, full in [(pieces[i], len(x) // 4) for i, x in ids.items()] + [(s, None) for s in sequences.values()]:
            at = 0
            for a, n in sorted(spans):
                assert a == at
                at += n
            assert at == full if full else at <= 2048
    used = sum(n for s in sequences.values() for _, n in s)
    assert used == sum(len(x) // 4 for x in ids.values())
    assert packing.cut(5000, split=None) == [(0, 2048), (2048, 2048), (4096, 904)] and len(packing.cut(5000)) == 4
    whole = packing.pack(docs, word_bpe(), split=None).collect()
    assert all(r["doc_pieces"] == -(-r["doc_tokens"] // 2048) for r in whole) and sum(r["length"] for r in whole) == sum(len(e.encode(r["text"])) // 4 for r in docs.collect())


def test_golay():
    x = np.arange(0, 1 << 23, 997)
    _, errors, count = golay.tables()
    assert Counter(count.tolist()) == {1: 277, 6: 1771}
    rng = np.random.default_rng(0)
    for d in (0, 1, 2):
        y = x.copy()
        for i in range(len(y)):
            for b in rng.permutation(23)[:d]:
                y[i] ^= 1 << int(b)
        a, b = (set(zip(*(v.tolist() for v in golay.keys(w)), strict=True)) for w in (x, y))
        assert {r for r, _ in a & b} == set(range(len(x)))


def brute_fingerprint(t):
    w = lower(t).encode().split()
    sh = [b" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))] if w else []
    hs = [xxhash.xxh64_intdigest(s, 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def test_simhash(spark, docs, awkward):
    for df in (docs, awkward.where("doc_id is not null")):
        rows = {r["doc_id"]: brute_fingerprint(r["text"]) for r in df.collect()}
        ids = sorted(rows)
        root = {i: i for i in ids}

        def find(i, root=root):
            while root[i] != i:
                i = root[i]
            return i

        for i in ids:
            for j in ids:
                if i < j and (rows[i] ^ rows[j]).bit_count() <= 3:
                    a, b = find(i), find(j)
                    root[max(a, b)] = min(a, b)
        for r in simhash.near_components(df).collect():
            assert (r["fingerprint"], r["component_id"]) == (f"{rows[r['doc_id']]:016x}", find(r["doc_id"]))


def test_exact_plan_meets_all_close_pairs():
    rng = random.Random(4)
    for _ in range(300):
        x = rng.getrandbits(64)
        y = x
        for b in rng.sample(range(64), rng.randint(1, 3)):
            y ^= 1 << b
        fp = np.array([[x], [y]], dtype=np.uint64)
        hits = [set(k[r == 0].tolist()) & set(k[r == 1].tolist()) for r, k in simhash.exact_keys(fp)]
        assert any(hits)


def test_close_pairs_keep_components():
    rng = np.random.default_rng(1)
    fp = (rng.integers(0, 8, 3000) * 0x0101010101 + rng.integers(0, 4, 3000)).astype(np.uint64).reshape(-1, 1)
    forest = simhash.close_pairs(fp, 1)
    assert len(forest) < len(fp)
    f = simhash.Forest(len(fp))
    for i, j in forest:
        f.join(i, j)
    for i, j in rng.integers(0, 3000, (500, 2)).tolist():
        if (int(fp[i, 0]) ^ int(fp[j, 0])).bit_count() <= 1:
            assert f.root(i) == f.root(j)


def test_similar_links(spark):
    rng = random.Random(8)
    rows, n = [], 0
    for _ in range(60):
        words = [f"w{rng.randint(0, 5000)}" for _ in range(rng.randint(80, 300))]
        rows.append((n, " ".join(words)))
        near = list(words)
        near[rng.randrange(len(near))] = "edited"
        rows.append((n + 1, " ".join(near)))
        far = [w if rng.random() > 0.4 else "other" for w in words]
        rows.append((n + 2, " ".join(far)))
        n += 3
    df = spark.createDataFrame(rows, "doc_id long, text string")
    links = {tuple(r) for r in simhash.similar_links(df).collect()}
    assert links == {(i, i + 1) for i in range(0, n, 3)}
    assert sorted(r["doc_id"] for r in simhash.drop_near_copies(df).collect()) == [i for i in range(n) if i % 3 != 1]


def test_similar_links_lose_no_component(spark):
    # the one true link of a stands beside many close copies of c at 0.79 to a
    rng = random.Random(3)
    rows, expected, n = [], {}, 0
    for _ in range(12):
        a = [f"w{rng.randint(0, 10**6)}" for _ in range(304)]
        c = list(a)
        for k in range(6):
            c[20 + 45 * k] = f"c{rng.randint(0, 10**6)}"
        rows.append((n, " ".join(a)))
        rows.append((n + 1, " ".join(c)))
        for k in range(30):
            x = list(c)
            x[rng.choice([5, 40, 85, 130, 175, 220, 280])] = f"x{rng.randint(0, 10**6)}"
            rows.append((n + 2 + k, " ".join(x)))
        n += 32
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert_components_as_by_brute_force(df, rows)


def test_similar_links_meet_all_pairs(spark):
    rng = random.Random(5)
    rows = []
    for n in range(0, 800, 2):
        a = [f"w{rng.randint(0, 10**6)}" for _ in range(304)]
        c = list(a)
        for k in range(6):
            c[20 + 45 * k] = f"c{rng.randint(0, 10**6)}"
        rows += [(n, " ".join(a)), (n + 1, " ".join(c))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert {tuple(r) for r in simhash.similar_links(df).collect()} == {(n, n + 1) for n in range(0, 800, 2)}


def star(rng, words, copies, low, high):
    """A text and copies of it whose similarity to it lies in [low, high); copies are less similar to each other."""
    base = [f"w{rng.randint(0, 10**7)}" for _ in range(words)]
    shingles = lambda t: set(simhash.shingle_hashes(t, simhash.SHINGLE).tolist())
    whole, out = shingles(" ".join(base)), [" ".join(base)]
    while len(out) <= copies:
        words, alike = list(base), 1.0
        while alike >= high:
            words[rng.randrange(len(words))] = f"x{rng.randint(0, 10**7)}"
            other = shingles(" ".join(words))
            alike = len(whole & other) / len(whole | other)
        if alike >= low:
            out.append(" ".join(words))
    return out


@pytest.mark.parametrize("low, high, copies", [(0.8, 0.82, 150), (0.85, 0.9, 150), (0.8, 0.85, 400)])
def test_stars_of_near_copies_become_one(spark, monkeypatch, low, high, copies):
    # small blocks: frequent shingles are compared in several pairs of blocks
    monkeypatch.setattr(simhash, "BLOCK", 128)
    rng = random.Random(copies)
    texts = [t for _ in range(3) for t in star(rng, 150, copies, low, high)]
    rng.shuffle(texts)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert simhash.drop_near_copies(df).count() == 3


def test_hot_keys_are_dealt_out(spark, monkeypatch):
    monkeypatch.setattr(simhash, "BLOCK", 16)
    rng = np.random.default_rng(4)
    base = rng.integers(-(1 << 62), 1 << 62, 40)
    prints = np.unique(np.concatenate([base ^ (np.int64(1) << int(b)) for b in rng.integers(0, 62, 12)]))
    rows = [(int(k), int(i), int(prints[i])) for k in (1, 2) for i in rng.permutation(len(prints))[: 100 * k]] + [(3, 1, int(prints[1])), (3, 2, int(prints[2]))]
    found = {tuple(r) for r in simhash.bucket_links(spark.createDataFrame(rows, "key long, id long, fp0 long"), 1, 2, hot_key=20).collect()}
    by = defaultdict(list)
    for k, i, fp in rows:
        by[k].append((i, fp & (2**64 - 1)))
    true = {(min(i, j), max(i, j)) for x in by.values() for i, a in x for j, b in x if i != j and (a ^ b).bit_count() <= 2}
    assert found <= true
    forest, wanted = simhash.Forest(len(prints)), simhash.Forest(len(prints))
    for f, pairs in ((forest, found), (wanted, true)):
        for i, j in sorted(pairs):
            f.join(i, j)
    assert [forest.root(i) for i in range(len(prints))] == [wanted.root(i) for i in range(len(prints))]


def assert_components_as_by_brute_force(df, rows):
    sets = {i: set(simhash.shingle_hashes(t, simhash.SHINGLE).tolist()) for i, t in rows}
    true = {(i, j) for i in sets for j in sets if i < j and len(sets[i] & sets[j]) >= simhash.SIMILARITY * len(sets[i] | sets[j]) > 0}
    links = {tuple(r) for r in simhash.similar_links(df).collect()}
    assert links <= true
    forest, wanted = simhash.Forest(len(rows)), simhash.Forest(len(rows))
    for f, pairs in ((forest, links), (wanted, true)):
        for i, j in sorted(pairs):
            f.join(i, j)
    assert [forest.root(i) for i in range(len(rows))] == [wanted.root(i) for i in range(len(rows))]


def test_components(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(30)] + [(100, 101), (101, 100), (7, 7)], "a long, b long")
    assert dict(got(components(links))) == {**dict.fromkeys(range(31), 0), 100: 100, 101: 100}


def brute_counts(t):
    t = t or ""
    space = "\x20\t\n\x0b\x0c\r"
    words, cur = [], ""
    for c in t + " ":
        if c in space:
            words += [cur] if cur else []
            cur = ""
        else:
            cur += c
    seen, dup = set(), 0
    for line in t.split("\n"):
        if any(c not in space for c in line):
            dup += line in seen
            seen.add(line)
    tri = Counter(tuple(words[i : i + 3]) for i in range(len(words) - 2))
    cover = {j for i in range(len(words) - 2) if tri[tuple(words[i : i + 3])] > 1 for j in range(i, i + 3)}
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in t), dup, len(cover)


def test_quality(spark, docs, awkward):
    for t in [*TEXTS, "a b c a b c", "x\nx\n\n\ny\nx", "é # é |", *(r["text"] for r in docs.collect())]:
        assert quality.count_text(t)[:5] == brute_counts(t)
    assert quality.binomial_tail(0, 10, 0.5) == pytest.approx(0.5**10)
    assert quality.binomial_tail(10, 10, 0.5) == pytest.approx(1)
    steps = len(quality.LADDER)
    assert quality.certified_level(1000, [0] * steps, 4) == quality.LADDER[-1]
    assert quality.certified_level(20, [0] * steps, 4) is None
    assert quality.certified_level(1000, [0, 0, *[500] * (steps - 2)], 4) == quality.LADDER[1]
    good = [(i, " ".join(f"w{i}x{j}" for j in range(60)), "en") for i in range(400)]
    bad = [(1000 + i, " ".join(f"w{i}x{j}###" for j in range(60)), "en") for i in range(5)]
    df = spark.createDataFrame(good + bad, "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, 1) for i in range(300)], "doc_id long, quality int")
    kept = {r["doc_id"] for r in quality.judge(df, labels).where("kept").collect()}
    assert kept == set(range(400)) == {r["doc_id"] for r in quality.keep_good(df, labels).collect()}


def test_quality_holds_on_a_held_out_half(spark):
    """Cutoffs chosen on half of the good rows reject no more than ALPHA of the other half, in each stratum."""
    rng = np.random.default_rng(5)
    n = 4000
    scored = spark.createDataFrame([(i, "ab"[i % 2], float(x), False) for i, x in enumerate(rng.lognormal(-0.5 + 0.4 * (np.arange(n) % 2), 0.6, n))], "doc_id long, stratum string, severity double, base_failed boolean")
    half = spark.range(0, n, 1).where("id % 4 < 2").selectExpr("id as doc_id", "1 as quality")
    levels = {name: step for name, _, step in quality.calibrate(scored, half)}
    assert set(levels) == {"a", "b"} and None not in levels.values()
    rest = scored.where("doc_id % 4 >= 2").collect()
    for name, step in levels.items():
        there = [r["severity"] for r in rest if r["stratum"] == name]
        assert 0 < np.mean([x > step for x in there]) <= quality.ALPHA


def test_quality_verdict_by_brute_force(spark, docs):
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    good = {r["doc_id"] for r in labels.collect() if r["quality"] == 1}
    rows, by = {}, defaultdict(list)
    for r in docs.collect():
        n, chars, symbols, dup, repeated, lines, top = quality.count_text(r["text"])
        failed = n < 50 or 100 * repeated > 50 * n
        worst = max(symbols / max(chars, 1) / 0.02, dup / max(lines, 1) / 0.45, repeated / max(n, 1) / 0.3, top / max(n, 1) / 0.3)
        rows[r["doc_id"]] = (failed, worst, r["lang"] or "")
        if r["doc_id"] in good and not failed:
            by[r["lang"] or ""].append(worst)
    level = {}
    for name, there in by.items():
        for step in quality.LADDER:
            k = sum(x > step for x in there)
            if sum(math.comb(len(there), i) * quality.ALPHA**i * (1 - quality.ALPHA) ** (len(there) - i) for i in range(k + 1)) > quality.DELTA / len(by):
                break
            level[name] = step
    want = {i: not failed and worst <= level.get(name, math.inf) for i, (failed, worst, name) in rows.items()}
    assert {r["doc_id"]: r["kept"] for r in quality.judge(docs, labels).collect()} == want


def test_quality_pools_small_strata(spark):
    strata = [f"l{k}" for k in range(quality.MOST_STRATA + 40)]
    rows, n = [], 0
    for k, lang in enumerate(strata):
        for _ in range(12 if k < quality.MOST_STRATA else 10):
            rows.append((n, " ".join(f"w{n}x{j}" for j in range(60)), lang))
            n += 1
    labels = spark.createDataFrame([(i, 1) for i in range(n)], "doc_id long, quality int")
    # each stratum beyond has too few rows of its own, all of them together have enough
    bad = [(n + k, " ".join(f"w{k}x{j}###" for j in range(60)), lang) for k, lang in enumerate([*strata, "unlabelled"])]
    df = spark.createDataFrame(rows + bad, "doc_id long, text string, lang string")
    kept = {r["doc_id"] for r in quality.judge(df, labels).where("kept").collect()}
    assert kept == set(range(n)) | {n + k for k in range(quality.MOST_STRATA)}
    scored = quality.judge(df, labels).join(df.select("doc_id", F.col("lang").alias("stratum")), "doc_id").select("doc_id", "stratum", "severity", "base_failed")
    levels = quality.calibrate(scored, labels)
    assert len(levels) == quality.MOST_STRATA + 1 and levels[-1][:2] == (None, 400)


def test_licenses(spark, awkward):
    p = licenses.parse_expression
    assert p("MIT OR Apache-2.0 AND GPL-2.0 WITH Classpath-exception-2.0") == ("or", ("id", "mit"), ("and", ("id", "apache-2.0"), ("with", ("id", "gpl-2.0"), ("id", "classpath-exception-2.0"))))
    assert p("(MIT OR ISC) AND BSD-3-Clause")[0] == "and"
    assert licenses.scan("SPDX-License-Identifier: see below")["own"] == set() and licenses.label_of("gpl-2.0+") == "gpl-2"
    told = [("SPDX-License-Identifier: MIT OR GPL-3.0", True), ("SPDX-License-Identifier: MIT AND GPL-3.0", False), ("SPDX-License-Identifier: Apache-2.0 WITH LLVM-exception", True)]
    told += [("SPDX-License-Identifier: MIT\nSPDX-License-Identifier: AGPL-3.0", False), ("SPDX-License-Identifier: see below", None), ("no tag", None), (None, None)]
    rows = licenses.scan_licenses(spark.createDataFrame([(i, t) for i, (t, _) in enumerate(told)], "doc_id long, text string"))
    assert [r["permitted"] for r in rows.orderBy("doc_id").collect()] == [x for _, x in told]
    rows = licenses.scan_licenses(spark.createDataFrame([(0, told[1][0])], "doc_id long, text string"), allowed=frozenset({"mit", "gpl-3"}))
    assert rows.first()["permitted"] is True
    assert licenses.labels_of(p("GPL-2.0 WITH x OR MIT")) == {"gpl-2", "mit"}
    assert licenses.satisfied(p("MIT AND (GPL-3.0 OR ISC)"), {"mit", "isc"}) and not licenses.satisfied(p("MIT AND ISC"), {"mit"})
    for bad in ("", "MIT OR", "(MIT", "AND MIT", "MIT)", "()"):
        with pytest.raises(licenses.BadExpression):
            p(bad)
    x = licenses.scan("Released under the MIT License. Under-the mit LICENSE\n// SPDX-License-Identifier: Apache-2.0 OR ISC\nApache License, Version 2.0")
    assert [w for w, _ in x["places"]] == [1, 5, 17] and x["base"] == {"mit", "apache-2"} and x["own"] == {"apache-2", "isc"}
    assert licenses.scan(None)["score"] == 0 and licenses.scan("unit mit licenses")["places"] == []
    r = licenses.scan_licenses(awkward).where("doc_id = 9").first()
    assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) == (4, 1, 0, 0, "mit")
    assert licenses.scan("日本語 é1")["n_words"] == 2
    long = licenses.scan("SPDX-License-Identifier: " + " or ".join(["MIT"] * 5000) + "\n" + "cc by nc text " * 30000)
    assert long["own"] == {"mit"} and licenses.satisfied(long["expressions"][0], {"mit"}) and not licenses.satisfied(long["expressions"][0], {"isc"})
    words = 3 + 2 * 5000 - 1
    assert [w for w, _ in long["places"]] == [words + 4 * i for i in range(30000)]


def test_license_labels_by_brute_force():
    rng = random.Random(3)
    phrases = [*licenses.BASE, *licenses.NOTICES]
    for _ in range(300):
        text = " ".join(rng.choice([rng.choice(phrases), rng.choice("the mit license cc by nc sa bsd 3 public gnu".split())]) for _ in range(12))
        for old in " .,-\n":
            text = text.replace(" ", rng.choice(" .,-\n"), 2)
        words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", text)
        line = f" {' '.join(words)} "
        x = licenses.scan(text)
        assert x["own"] == {label for phrase, (label, _) in licenses.NOTICES.items() if f" {phrase} " in line}
        at = [(i, label) for phrase, label in licenses.BASE.items() for i in range(len(words)) if words[i : i + phrase.count(" ") + 1] == phrase.split()]
        assert sorted(x["places"]) == sorted(at)


def test_language_id_learns_seventy_languages(spark):
    rng = random.Random(9)
    letters = "abcdefghijklmnopqrstuvwxyzàéîõüßñçøåæœ"
    words = {f"l{k:02d}": ["".join(rng.choice(letters) for _ in range(rng.randint(3, 6))) for _ in range(12)] for k in range(70)}
    rows = [(k * 100 + i, " ".join(rng.choices(w, k=30)), name) for k, (name, w) in enumerate(words.items()) for i in range(30)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    truth = {i: name for i, _, name in rows}
    found = langid.language_id(df).where("held_out").collect()
    assert {r["lang_pred"] for r in found} == set(words) and np.mean([r["lang_pred"] == truth[r["doc_id"]] for r in found]) >= 0.9


def test_language_sample_is_bounded(spark):
    df = spark.createDataFrame([(i, f"text {i}", f"l{i % 50}") for i in range(5000)], "doc_id long, text string, lang string")
    sample = langid.training_sample(df, sample_rows=500)
    assert len({name for name, _ in sample}) == 50 and len(sample) <= 2 * 500 * langid.PIECES


def test_language_id(docs):
    rows = {r["doc_id"]: r for r in langid.language_id(docs).collect()}
    right = [rows[r["doc_id"]]["lang_pred"] == r["lang"] for r in docs.collect() if zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1]
    assert len(right) > 30 and np.mean(right) >= 0.95
    assert all(r["held_out"] == (zlib.crc32(str(i).encode()) % 3 == 1) and 0 <= r["score"] <= 1 for i, r in rows.items())
    net = langid.train([("a", "aaa bbb " * 9), ("b", "zzz yyy " * 9)])
    x = langid.windows_of("some text of zzz " * 100)
    direct = net._respond(x)[0]
    want = langid.softmax(np.maximum(direct + net.bias, 0) @ net.dense + net.offset)
    assert np.allclose(net.probabilities(x, net.tables()), want, atol=1e-4)
    raw = ("Abcé" * 300).encode().translate(langid._LOWER)
    w = langid.windows_of("Abcé" * 300)
    assert b"".join(bytes(r)[: langid.WINDOW - langid.OVERLAP] for r in w[:-1]) + bytes(w[-1]).rstrip(b"\0") == raw


def test_suffix_array():
    rng = random.Random(1)
    for _ in range(3000):
        t = [rng.randint(1, rng.randint(1, 3)) for _ in range(rng.randint(0, 16))]
        sa = suffix_array(t)
        assert sa == sorted(range(len(t)), key=lambda i: t[i:])
        for r, k in enumerate(common_prefixes(t, sa)):
            a, b = (t[sa[r] :], t[sa[r - 1] :]) if r else ([], [])
            assert k == next((i for i, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))


def brute_removed(texts):
    raws = [(t or "").encode() for t in texts]
    seen = Counter(b[s : s + 200] for b in raws for s in range(len(b) - 199))
    out = []
    for b in raws:
        gone = np.zeros(len(b) + 1, dtype=bool)
        for s in range(len(b) - 199):
            if seen[b[s : s + 200]] > 1:
                gone[s : s + 200] = True
        spans = int((np.diff(np.r_[0, gone.astype(int)]) == 1).sum())
        out.append((len(b), int(gone.sum()), spans, hashlib.sha256(bytes(x for x, g in zip(b, gone, strict=False) if not g)).hexdigest()))
    return out


@pytest.mark.parametrize("hot", [suffix_dedup.HOT_SLICES, 2])
def test_suffix_dedup(spark, hot):
    rng = random.Random(6)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 9)))
    text = lambda n: " ".join(word() for _ in range(n))
    passage, base = text(70), text(200)
    texts = [None, "", "x" * 199, "y" * 200, "z" * 201, "ab" * 300, base, base, base[:400] + "!" + base[401:]]
    texts += [text(30) + passage + text(30) for _ in range(6)] + [text(5) + passage[:250] + text(5), passage, text(100), "é" * 150]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    rows = suffix_dedup.remove_repeats(df, hot=hot).orderBy("doc_id").collect()
    assert [tuple(r)[1:5] for r in rows] == brute_removed(texts)
    assert all(hashlib.sha256(r["kept_text"]).hexdigest() == r["kept_sha256"] for r in rows)


def test_suffix_dedup_hot_anchor(spark, monkeypatch):
    """A line that many texts hold, a passage that many hold between different words, and arrays of few symbols."""
    monkeypatch.setattr(suffix_dedup, "ARRAY_SYMBOLS", 3000)
    rng = random.Random(12)
    text = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 9))) for _ in range(n))
    line, passage = text(12), text(50)
    texts = [text(12) + line + text(14) for _ in range(80)] + [text(3) + passage + text(3) for _ in range(60)]
    texts += [passage[10:240], passage[:215] + "x", *texts[:3], *texts[100:104]]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    for hot in (7, 30, 5000):
        assert [tuple(r)[1:5] for r in suffix_dedup.remove_repeats(df, hot=hot).orderBy("doc_id").collect()] == brute_removed(texts), hot


def test_repeated_windows_by_bands(monkeypatch):
    rng = random.Random(13)
    gram = "".join(rng.choice("abcd") for _ in range(32))
    left, right = ("".join(rng.choice("ab") for _ in range(168)) for _ in "ab")
    slices = set()
    while len(slices) < 60:
        a, z = list(left), list(right)
        for side in (a, z):
            for _ in range(rng.randint(0, 2)):
                side[rng.randrange(168)] = rng.choice("xyz")
        a = a[rng.randint(0, 60) :]
        slices.add(("".join([*a, gram, *z]).encode()[: rng.randint(250, 368)], len(a)))
    slices = [(s, p) for s, p in sorted(slices) if len(s) >= 200 and p <= 168]
    windows = Counter(s[i : i + 200] for s, p in slices for i in range(len(s) - 199) if 0 <= p - i <= 168)
    for limit in (100, 2000, 10**6):
        monkeypatch.setattr(suffix_dedup, "ARRAY_SYMBOLS", limit)
        flags = suffix_dedup.repeated_windows([s for s, _ in slices], [p for _, p in slices], [1] * len(slices))
        for (s, p), f in zip(slices, flags, strict=True):
            assert all(f[i] == (windows[s[i : i + 200]] > 1) for i in range(len(f)) if 0 <= p - i <= 168)


def test_suffix_dedup_text_over_a_part(spark):
    """A text of over 16 MiB, with a passage that stands over the cut of its parts and again in a short text."""
    rng = np.random.default_rng(8)
    long = "".join(map(chr, rng.integers(97, 123, PART + 5000)))
    passage = long[PART - 700 : PART + 900]
    texts = [long, "A" * 50 + passage + "B" * 50, "C" * 30 + long[100:299]]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    rows = suffix_dedup.remove_repeats(df).orderBy("doc_id").collect()
    kept = [long.replace(passage, ""), "A" * 50 + "B" * 50, texts[2]]
    assert [tuple(r)[1:5] for r in rows] == [(len(t), len(t) - len(k), int(t != k), hashlib.sha256(k.encode()).hexdigest()) for t, k in zip(texts, kept, strict=True)]


def test_runs_cover_all_windows():
    raw = bytes(random.Random(2).choices(b"abcd ", k=5000))
    _, _, start, length, place = runs(raw)
    assert start[0] == 0 and (start[1:] == start[:-1] + length[:-1] - 199).all() and start[-1] + length[-1] == 5000
    assert (place >= length - 200).all() and (place <= 168).all()


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_queries_match_sql(spark, duck, name):
    df = QUERIES[name](spark, SMALL)
    cols = sorted(df.columns)
    cur = duck.execute(ORACLES[name])
    at = [[c[0] for c in cur.description].index(c) for c in cols]
    assert got(df.select(*cols)) == sorted((tuple(r[i] for i in at) for r in cur.fetchall()), key=repr)


def test_query_suffix_dedup_brute(spark, docs):
    rows = {r["doc_id"]: tuple(r)[1:] for r in QUERIES["op10_suffix_dedup"](spark, SMALL).collect()}
    have = docs.collect()
    assert dict(zip((r["doc_id"] for r in have), brute_removed([r["text"] for r in have]), strict=True)) == rows


def test_sketches_never_rule_out_a_similar_pair():
    rng = np.random.default_rng(5)
    sets = []
    for n in (1, 2, 15, 31, 32, 33, 200, 255, 256, 300, 5000):
        base = rng.integers(0, 1 << 63, n, dtype=np.uint64)
        sets += [np.unique(base)] + [np.unique(np.r_[base[: max(1, int(n * share))], rng.integers(0, 1 << 63, n - int(n * share), dtype=np.uint64)]) for share in (0.5, 0.85, 0.9, 0.97)]
    sets += [np.unique(np.arange(n, dtype=np.uint64) << np.uint64(20)) for n in (600, 700)]  # all in one slot
    at, sizes = np.arange(len(sets)), np.array([len(s) for s in sets])
    left = simhash.sketched_pairs([simhash.sketch(s) for s in sets], sizes, at, at, np.ones((len(sets), len(sets)), bool), 0.8)
    common = np.array([[len(np.intersect1d(x, y)) for y in sets] for x in sets])
    alike = common >= 0.8 * (sizes[:, None] + sizes[None] - common) - 1e-6
    assert left[alike].all() and left[-1, -2]
    large = sizes >= 200
    assert not left[np.ix_(large, large)][(common == 0)[np.ix_(large, large)]].any()


def test_block_units_move_sets_only_where_sketches_leave_a_partner(spark, monkeypatch):
    """Unlike texts under frequent shingles: their whole sets went to every unit. Copies among them are still linked."""
    rng = random.Random(3)
    texts = [" ".join("".join(rng.choices("abcdefghij", k=6)) for _ in range(100)) for _ in range(60)]
    texts.append(texts[7] + " tail")
    named = spark.createDataFrame(list(enumerate(texts)), "id long, text string")
    sizes = [len(np.unique(simhash.shingle_hashes(t, 5))) for t in texts]
    shared = spark.createDataFrame([(s, i, i, n, 0) for s in range(3) for i, n in enumerate(sizes)], "shingle long, id long, root long, n long, place long")
    moved, plain = [], simhash.unit_links
    monkeypatch.setattr(simhash, "unit_links", lambda units, *rest: moved.append(units.count()) or plain(units, *rest))
    assert {tuple(sorted(r)) for r in simhash.block_links(shared, named, 5, 0.8).collect()} == {(7, 60)}
    assert moved == [6]  # two texts under three shingles, of 183 rows
