from __future__ import annotations

import collections
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest

from regpath.llm import decontaminate, entries, kernel, language, licenses, lines, mixing, neardup, passages, quality, sharding, vectors

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
#: Extra columns whose names the operators use inside, or that other tables have.
CLASH = "doc_id long, text string, lang string, source string, n_chars long, rep long, hub long, seed long, pos int, component long, item_id long, n long, label string, bucket string, copy int, rate double, bands string"


def docs_of(spark, texts, **columns):
    rows = [(i, t, columns.get("lang", "en"), columns.get("source", "s"), None if t is None else len(t)) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS)


def odd(spark):
    """Nulls everywhere, empty and blank texts, a very long one, repeated rows and equal keys; clashing columns."""
    long = " ".join(f"w{i % 977}" for i in range(40_000))
    rows = [
        (1, None, None, None, None), (2, "", "en", "a", 0), (3, "  \n\t ", "en", "a", 5), (4, long, "en", "a", len(long)), (5, "one", None, "b", 3), (6, "one", "fr", None, None),
        (7, "Ünïcode wörds ÄÖÜ and a few more of them to see", "de", "b", 1), (7, "Ünïcode wörds ÄÖÜ and a few more of them to see", "de", "b", 1), (None, "no key but some words in it", "en", "b", 2), (8, "!!! ### $$$", "en", "b", 3), (9, "x" * 100_000, "en", "b", 4), (7, "another text of the same key altogether", "de", "b", 1),
    ]
    return spark.createDataFrame([(*r, *[None] * 12) for r in rows], CLASH)


#: Names that operators and stages use inside, beside those of CLASH.
INNER = (
    "key", "text_", "row", "mark", "h", "s", "b", "c0", "c1", "at", "start", "size", "crc", "grown", "slot", "shard", "place", "upto", "draws", "mix_source", "mix_text", "mix_key", "copy", "copy_no", "copy_no_", "row_key", "_mark", "_no", "rejected", "_key", "_words",
    "words", "hit", "declared", "suffix", "host", "scores", "language", "posterior", "accepted", "held_out", "score", "predicted", "n_words", "d1", "d2", "met", "often", "star", "gap", "doc_a", "doc_b", "_id", "other", "band", "kept", "n_shingles", "component_id", "tasks", "own", "i", "j", "q", "told", "w",
)


def crowded(spark):
    """Some documents, with an extra column for each name used inside."""
    rng = random.Random(2)
    texts = [" ".join(words(rng, 70)) for _ in range(6)]
    texts += [texts[0] + " end", texts[1], "the and of " * 30, "released under the mit license", None, ""]
    rows = [(i, t, "en", f"s{i % 2}", 5, *[f"{n}{i}" for n in INNER]) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS + "".join(f", `{n}` string" for n in INNER))


def test_crowded_columns(spark):
    docs = crowded(spark)
    plain = docs.select("doc_id", "text", "lang", "source", "n_chars")
    bench = spark.createDataFrame([(1, " ".join(words(random.Random(2), 40)))], "item_id long, text string")
    tree, machine = sharding.tree_of(3), quality.fit([])
    same = {
        "scan": licenses.scan, "overlaps": lambda d: decontaminate.overlaps(d, bench), "assign": lambda d: sharding.assign(d, tree, grown=sharding.with_region(tree, 1, "r2")), "classify": lambda d: quality.classify(d, machine),
        "passages": lambda d: passages.repeated_spans(passages.shared_passages(d)), "near": neardup.near_duplicates, "identify": lambda d: language.identify(language.of_documents(d)),
    }
    for name, f in same.items():
        a, b = f(docs), f(plain)
        assert a.columns == b.columns and collections.Counter(map(str, a.collect())) == collections.Counter(map(str, b.collect())), name
    inner = lambda r: [r[n] for n in INNER]
    mixed = mixing.mix(docs, weights={"s0": 1.0, "s1": 3.0})
    assert mixed.columns == [*docs.columns, "copy_no__", "mix_key_"]
    for out in (mixed, language.keep_identified(docs), decontaminate.clean(docs, bench), neardup.keep_one(docs), neardup.keep_one(docs.union(docs.limit(3)))):
        assert out.columns[: len(docs.columns)] == docs.columns and out.count()
        assert all(inner(r) == [f"{n}{r['doc_id']}" for n in INNER] for r in out.collect())
    assert {r["doc_id"] for r in decontaminate.clean(docs, bench).collect()} == set(range(1, 12)) - {6}


def test_keys_that_collide_or_lack(spark):
    """Different texts of one doc_id are documents of their own; a passage is found whatever the key."""
    rng = random.Random(5)
    a, b, c = (" ".join(words(rng, 60)) for _ in range(3))
    rows = [(1, a, "en", "s", 1), (1, b, "en", "s", 1), (2, a + " more", "en", "s", 1), (None, c, "en", "s", 1), (None, c + " more", "en", "s", 1), (None, b, "en", "s", 1), (3, None, "en", "s", 1), (4, "", "en", "s", 1)]
    kept = neardup.keep_one(spark.createDataFrame(rows, DOCS), k=5).collect()
    assert sorted(((r["doc_id"], r["text"]) for r in kept if r["text"] != c and r["text"] != c + " more"), key=str) == sorted([(1, a), (1, b), (3, None), (4, "")], key=str)
    assert sum((r["text"] or "").startswith(c) for r in kept) == 1 and len(kept) == 5
    bench = spark.createDataFrame([(1, c)], "item_id long, text string")
    assert [r["text"] for r in decontaminate.clean(spark.createDataFrame(rows, DOCS), bench).collect()].count(c) == 0


def nothing(spark):
    return spark.createDataFrame([], DOCS)


@pytest.mark.parametrize("name", sorted(entries.ORACLES))
def test_against_sql(spark, sf, duck, same_rows, name):
    same_rows(entries.QUERIES[name](spark, sf), duck, entries.ORACLES[name])


# ---- 1 mixing


def test_mixing_rates_and_copies(spark):
    rows = [(i, "x" * 9, "en", "big" if i % 10 else "small", 9) for i in range(4000)]
    out = mixing.mix(spark.createDataFrame(rows, DOCS), weights={"big": 1.0, "small": 1.0}).collect()
    n = collections.Counter(r["source"] for r in out)
    assert abs(n["big"] - 2000) < 200 and abs(n["small"] - 2000) < 200
    per = collections.Counter(r["doc_id"] for r in out)
    assert {r["copy_no"] for r in out if r["doc_id"] == max(per, key=per.get)} == set(range(1, max(per.values()) + 1))
    small = [per.get(i, 0) for i in range(0, 4000, 10)]
    assert abs(np.var(small) / np.mean(small) - 1) < 0.3  # Poisson: the variance is the mean
    again = mixing.mix(spark.createDataFrame(rows, DOCS).repartition(7), weights={"big": 1.0, "small": 1.0}).collect()
    assert collections.Counter((r["doc_id"], r["copy_no"], r["mix_key"]) for r in again) == collections.Counter((r["doc_id"], r["copy_no"], r["mix_key"]) for r in out)


def test_mixing_large_rates_and_odd_rows(spark):
    few = spark.createDataFrame([(i, "abc", "en", "rare" if i == 0 else "common", 3) for i in range(1000)], DOCS)
    out = mixing.mix(few, weights={"rare": 1.0, "common": 1.0}).where("source = 'rare'").count()
    assert 400 < out < 600  # a rate of 500 needs several draws
    assert mixing.mix(few, weights={"common": 1.0}).where("source = 'rare'").count() == 0
    mixed = mixing.mix(odd(spark), weights={"a": 50.0, "b": 50.0, None: 50.0})
    assert set(odd(spark).columns) <= set(mixed.columns) and mixed.count() > 0
    assert mixing.mix(nothing(spark)).count() == 0
    assert mixing.mix(docs_of(spark, [None, ""])).count() >= 0


# ---- 2 licenses


def test_license_scan(spark):
    far = "word " * 500
    texts = [
        "Under the MIT License. under the mit-license!", far + "Licensed under the Apache License,\nVersion 2.0." + far, "cc by nc and CC-BY-NC 4.0", "released under the gpl license", "Redistribution and use in source and binary forms, with or without changes, are permitted provided that the following conditions are met",
        "LİCENSE under the mıt license", None, "", "released under a licence",
    ]
    r = {x["doc_id"]: x for x in licenses.scan(docs_of(spark, texts)).collect()}
    assert (r[0]["n_words"], r[0]["n_base"], r[0]["first_word"], r[0]["last_word"], r[0]["base_labels"], r[0]["score"]) == (8, 2, 0, 4, "mit", 1.0)
    assert r[1]["base_labels"] == "apache-2" and r[1]["first_word"] == 503 and "apache-2" in r[1]["labels"]
    assert (r[2]["n_base"], r[2]["first_word"], r[2]["last_word"]) == (2, 0, 4)
    assert (r[3]["labels"], r[3]["score"]) == ("", 0.0)
    assert r[4]["labels"] == "bsd" and 0.9 <= r[4]["score"] < 1 and r[4]["n_base"] == 0
    assert r[5]["n_base"] == 0 and r[5]["first_word"] is None
    assert (r[6]["n_words"], r[7]["n_words"], r[6]["labels"]) == (0, 0, "")
    assert licenses.scan(odd(spark)).count() == 12 and licenses.scan(nothing(spark)).count() == 0


def test_license_filters_lose_nothing(spark):
    rng = random.Random(3)
    templates = [(f"t{i}", " ".join(rng.sample("abcdefghij", rng.randint(3, 7)))) for i in range(6)]
    texts = [" ".join(rng.choice("abcdefghijxyz") for _ in range(rng.randint(0, 12))) for _ in range(200)]
    got = {x["doc_id"]: x["labels"] for x in licenses.scan(docs_of(spark, texts), phrases={"zz zz": "none"}, templates=templates, contained=0.7).collect()}
    for i, t in enumerate(texts):
        want = {l for l, w in templates if len(set(t.split()) & set(w.split())) >= 0.7 * len(set(w.split())) - 1e-9}
        assert got[i] == ",".join(sorted(want)), (t, templates)


def test_long_templates(spark):
    """Templates of any length, given as a table; those in a part of a long text are found, others are not."""
    rng = random.Random(4)
    long, short = words(rng, 700), words(rng, 5)
    some = [w for i, w in enumerate(long) if i % 12]  # 91.6 % of the words
    less = [w for i, w in enumerate(long) if i % 8]  # 87.5 %
    texts = [" ".join(words(rng, 900) + x + words(rng, 500)) for x in (long, some, less, short, long[:600], words(rng, 3))]
    given = spark.createDataFrame([("long", " ".join(long).upper()), ("short", ", ".join(short)), ("mit", licenses.TEMPLATES[-2][1]), ("none", None), ("none", "")], "label string, text string")
    r = {x["doc_id"]: (x["labels"], x["score"]) for x in licenses.scan(docs_of(spark, [*texts, "MIT. " + licenses.TEMPLATES[-2][1], texts[1], None]), templates=given).collect()}
    assert [r[i][0] for i in range(9)] == ["long", "long", "", "short", "", "", "mit", "long", ""]
    assert r[0][1] == 1.0 and 0.9 < r[1][1] < 0.92 and r[2][1] == 0.0 and r[1] == r[7]


# ---- 3 vectors


def brute_links(rows, cosine=0.95):
    keep = {}
    for i, v in rows:
        if v is not None and v and all(x is not None and np.isfinite(x) for x in v) and any(v):
            keep[i] = np.array(v, dtype=float)
    links = collections.defaultdict(set)
    for i, a in keep.items():
        for j, b in keep.items():
            if i < j and len(a) == len(b) and a @ b / np.linalg.norm(a) / np.linalg.norm(b) >= cosine:
                links[i].add(j)
                links[j].add(i)
    return links


def components(ids, links):
    out = {}
    for i in sorted(ids):
        if i not in out:
            todo = [i]
            while todo:
                x = todo.pop()
                if x not in out:
                    out[x] = i
                    todo += links[x]
    return out


def test_vectors_against_brute_force(spark, monkeypatch):
    monkeypatch.setattr(vectors, "BLOCK", 16)  # blocks within groups, too
    rng = np.random.default_rng(1)
    rows = [(i, list(map(float, rng.normal(size=16)))) for i in range(150)]
    for i in range(60):
        base = np.array(rows[i % 12][1])
        rows.append((200 + i, list(map(float, base + rng.normal(size=16) * 0.12 * (i % 3)))))
    rows += [(300, None), (301, []), (302, [0.0] * 16), (303, [float("nan")] * 16), (304, [None] * 16), (305, [1.0, 2.0]), (306, [2.0, 4.0]), (307, [1e300] * 16), (308, [1e-300] * 16), (309, [float("inf")] * 16)]
    df = spark.createDataFrame(rows + rows[:3], "vec_id long, embedding array<double>")
    links = brute_links([(i, v if i not in (307, 308) else [1.0] * 16) for i, v in rows])
    want = components([i for i, _ in rows], links)
    got = {r["vec_id"]: r for r in vectors.linked(df).collect()}
    assert len(got) == len(rows)
    for i, _ in rows:
        assert (got[i]["n_links"], got[i]["component_id"], got[i]["kept"]) == (len(links[i]), want[i], want[i] == i), i
    assert vectors.linked(df.where("false")).count() == 0
    assert {r["n_links"] for r in vectors.linked(spark.createDataFrame([(1, None), (2, None)], "vec_id long, embedding array<float>")).collect()} == {0}


def test_hadamard_keeps_lengths():
    x = np.random.default_rng(0).normal(size=(5, 32))
    assert np.allclose(np.linalg.norm(vectors.hadamard(x), axis=1), np.linalg.norm(x, axis=1) * 32**0.5)


def test_vector_recall_at_the_threshold():
    rng = np.random.default_rng(2)
    x = rng.normal(size=(3000, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    g = rng.normal(size=x.shape)
    g -= (g * x).sum(axis=1, keepdims=True) * x
    y = 0.95 * x + (1 - 0.95**2) ** 0.5 * g / np.linalg.norm(g, axis=1, keepdims=True)
    depth, tables = vectors.plan(50_000, 64)
    a, b = vectors.codes(x, depth, tables), vectors.codes(y, depth, tables)
    met = np.array([len(np.intersect1d(p, q)) > 0 for p, q in zip(a, b, strict=True)])
    assert met.mean() > 0.998


@pytest.mark.parametrize(("vectors_", "dim"), [(500, 64), (50_000, 64), (5_000_000, 64), (500_000_000, 64), (50_000, 256)])
def test_vector_recall_of_each_depth(vectors_, dim):
    """Pairs at the threshold share a code, whatever depth a table's size asks for."""
    rng = np.random.default_rng(5)
    x = rng.normal(size=(1500, dim))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    g = rng.normal(size=x.shape)
    g -= (g * x).sum(axis=1, keepdims=True) * x
    y = 0.95 * x + (1 - 0.95**2) ** 0.5 * g / np.linalg.norm(g, axis=1, keepdims=True)
    depth, tables = vectors.plan(vectors_, dim)
    met = np.array([len(np.intersect1d(p, q)) > 0 for p, q in zip(vectors.codes(x, depth, tables), vectors.codes(y, depth, tables), strict=True)])
    assert met.mean() > 0.997


def test_vectors_of_the_given_table_against_brute_force(spark):
    sf = "/root/testdata/sf0.01"
    rows = [(r["vec_id"], r["embedding"]) for r in spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", "embedding").collect()]
    x = np.array([v for _, v in rows], dtype=np.float64)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    close = np.argwhere(np.triu(x @ x.T >= vectors.COSINE, 1))
    links = collections.defaultdict(set)
    for i, j in close.tolist():
        links[rows[i][0]].add(rows[j][0])
        links[rows[j][0]].add(rows[i][0])
    want = components([i for i, _ in rows], links)
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in vectors.op3_embedding_dedup(spark, sf).collect()}
    assert got == {i: (len(links[i]), want[i]) for i, _ in rows}


# ---- 4 decontamination


ITEM = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon"


def test_decontamination(spark):
    w = ITEM.split()
    some = " ".join("x" if i in (4, 11) else x for i, x in enumerate(w))
    texts = [f"before {ITEM.upper()}, after", some, " ".join(w[:9]), " ".join(reversed(w)), None, "", "noise " * 50 + ITEM, " ".join(w[5:] + w[:5])]
    bench = spark.createDataFrame([(1, ITEM), (2, None), (3, ""), (4, "two words"), (5, "five words stand right here")], "item_id long, text string")
    docs = docs_of(spark, [*texts, "it has five words stand right here in it", "Two words"])
    got = {(r["doc_id"], r["item_id"]): r for r in decontaminate.overlaps(docs, bench).collect()}
    assert set(got) == {(0, 1), (1, 1), (6, 1), (7, 1), (8, 5), (9, 4)}
    assert (got[0, 1]["overlap"], got[0, 1]["start"], got[1, 1]["matched"], got[6, 1]["start"]) == (1.0, 1, 18, 50)
    assert got[7, 1]["overlap"] == 0.75
    shuffled = decontaminate.overlaps(docs, bench, broadcast_up_to=0).collect()
    assert {tuple(r) for r in shuffled} == {tuple(r) for r in got.values()}
    assert {r["doc_id"] for r in decontaminate.clean(docs, bench).collect()} == {2, 3, 4, 5}
    assert decontaminate.overlaps(nothing(spark), bench).count() == 0 and decontaminate.overlaps(docs, bench.where("false")).count() == 0
    left = decontaminate.clean(odd(spark), bench)
    assert left.columns == odd(spark).columns and left.count() == 12


def test_parts_of_long_items(spark, duck, same_rows):
    """A part of a long item, and one with words put in between its parts, are overlaps; short runs are not; the SQL agrees, short items included."""
    rng = random.Random(11)
    item = words(rng, 150)
    changed = [w if i % 9 else "new" for i, w in enumerate(item[30:60])]
    rows = [(0, " ".join(words(rng, 30) + item[40:100])), (1, " ".join(item[10:25] + ["x", "y"] + item[25:40] + ["z"] + item[40:62])), (2, " ".join(words(rng, 5) + changed + words(rng, 50))), (3, " ".join(words(rng, 40) + item[7:20])), (4, None), (5, "two words"), (6, "so five words stand right here then"), (7, " ".join(item))]
    bench = spark.createDataFrame([(1, " ".join(item)), (2, "Two words"), (3, "five words stand right here"), (4, None), (5, "")], "item_id long, text string")
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    found = decontaminate.overlaps(docs, bench)
    assert {(r["doc_id"], r["item_id"]) for r in found.collect()} == {(0, 1), (1, 1), (2, 1), (5, 2), (6, 3), (7, 1)}
    assert sorted(map(tuple, decontaminate.overlaps(docs, bench, broadcast_up_to=0).collect())) == sorted(map(tuple, found.collect()))
    con = duck.cursor()
    for name, df in (("documents", docs), ("benchmark", bench)):
        frame = df.toPandas()
        con.register(f"own_{name}", frame)
    sql = decontaminate.ORACLE.replace("FROM documents", "FROM own_documents").replace("FROM benchmark", "FROM own_benchmark")
    same_rows(found, con, sql)


# ---- 5 sharding


def test_sharding(spark):
    df = docs_of(spark, [None, "", *(f"text {i}" for i in range(3000))])
    tree = sharding.tree_of(16)
    rows = sharding.assign(df, tree, grown=sharding.with_region(tree, 1, "r2")).collect()
    assert len(rows) == 3002
    by = collections.defaultdict(list)
    for r in rows:
        text = "" if r["doc_id"] < 2 else f"text {r['doc_id'] - 2}"
        assert (r["size"], r["text_crc32"], r["law"]) == (len(text) + 1, zlib.crc32(text.encode()), "key")
        by[r["shard"]].append(r["slot"])
        assert r["grown_shard"] in (r["shard"], 16)
    assert set(by) == set(range(16)) and all(sorted(s) == list(range(len(s))) for s in by.values())
    sizes = [len(s) for s in by.values()]
    assert max(sizes) < 1.4 * min(sizes) and 100 < sum(r["grown_shard"] == 16 for r in rows) < 260
    again = {r["doc_id"]: (r["shard"], r["slot"]) for r in sharding.assign(df.repartition(9), tree).collect()}
    assert again == {r["doc_id"]: (r["shard"], r["slot"]) for r in rows}


def test_shards_against_recomputed_draws(spark):
    import math

    import xxhash

    def hashed(*parts):
        seed = 42
        for p in parts:
            seed = xxhash.xxh64_intdigest(p, seed=seed)
        return seed

    def shard_of(key, node):
        if node.shard is not None:
            return node.shard
        h = hashed(b"shard", str(key).encode()).to_bytes(8, "little")
        own = [c for c in node.children if c.weight > 0]
        if len(own) == 1:
            return shard_of(key, own[0])
        return shard_of(key, max(own, key=lambda c: math.log(((hashed(c.name.encode(), h) >> 11) + 1) * 2.0**-53) / c.weight))

    tree = sharding.tree_of(16)
    grown = sharding.with_region(tree, 1, "r2")
    odd_tree = sharding.Node("all", (sharding.Node("a", shard=5, own=2.0), sharding.Node("b", shard=1, own=0.0), sharding.Node("c", (sharding.Node("d", shard=2), sharding.Node("e", (sharding.Node("f", shard=3),)))), sharding.Node("g", (sharding.Node("h", shard=7, own=0.5),))))
    docs = docs_of(spark, [f"text {i}" for i in range(1500)])
    for r in sharding.assign(docs, tree, grown=grown).collect():
        assert (r["shard"], r["grown_shard"]) == (shard_of(r["doc_id"], tree), shard_of(r["doc_id"], grown))
    for r in sharding.with_shard(docs, "doc_id", odd_tree).collect():
        assert r["shard"] == shard_of(r["doc_id"], odd_tree)


def test_sharding_moves_rows_within_changed_subtrees(spark):
    keys = spark.range(4000)
    tree = sharding.tree_of(16)
    heavier = sharding.Node("all", tuple(sharding.Node(r.name, tuple(sharding.Node(k.name, tuple(sharding.Node(s.name, shard=s.shard, own=3.0 if s.shard == 9 else 1.0) for s in k.children)) for k in r.children)) for r in tree.children))
    moved = sharding.with_shard(sharding.with_shard(keys, "id", tree, "a"), "id", heavier, "b").where("a != b").collect()
    assert moved and all(r["b"] // 8 == 1 for r in moved)  # only into the region whose weight grew
    assert all(r["b"] == 9 for r in moved if r["a"] // 4 == 2)


def test_sharding_odd_rows(spark):
    tree = sharding.tree_of(3)
    rows = sharding.assign(odd(spark), tree).collect()
    assert len(rows) == 12 and all(r["grown_shard"] is None for r in rows)
    assert len({(r["shard"], r["slot"]) for r in rows}) == 12
    assert sharding.assign(nothing(spark), tree).count() == 0


# ---- 6 quality


def test_quality_held_out(spark):
    sf = "/root/testdata/sf0.01"
    out = {r["doc_id"]: r for r in quality.op6_quality(spark, sf).collect()}
    label = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    assert all(r["held_out"] == (zlib.crc32(str(i).encode()) % 4 == 2) and r["predicted"] == (r["score"] >= 0.7) and 0 <= r["score"] <= 1 for i, r in out.items())
    held = [(r["score"], label[i], r["predicted"]) for i, r in out.items() if r["held_out"] and i in label]
    assert np.mean([p == q for _, q, p in held]) > 0.95
    good, bad = [s for s, q, _ in held if q == 1], [s for s, q, _ in held if q == 0]
    assert np.mean([[g > b for b in bad] for g in good]) > 0.93


def test_quality_identity_and_odd_rows(spark):
    rng = np.random.default_rng(4)
    size = quality.BUCKETS + len(quality.STATISTICS)
    m = quality.Machine(0.3, rng.normal(size=size) * 0.1, rng.normal(size=(size, quality.RANK)) * 0.1, np.zeros(len(quality.STATISTICS)), np.ones(len(quality.STATISTICS)))
    texts = pa.array(["a b c d", "", None, "x y"])
    buckets, off, stats = quality.features(texts, np.array([7.0, 0.0, np.nan, 3.0]))
    got = quality.scores(m, buckets, off, stats)
    for r in range(4):
        own = buckets[off[r] : off[r + 1]]
        x = np.zeros(size)
        x[own] = 1 / np.sqrt(max(1, len(own)))
        x[quality.BUCKETS :] = np.clip(stats[r], -4, 4)
        pairs = sum(x[i] * x[j] * (m.factor[i] @ m.factor[j]) for i in np.flatnonzero(x) for j in np.flatnonzero(x) if i < j)
        assert np.isclose(got[r], 1 / (1 + np.exp(-(m.bias + m.weight @ x + pairs))))
    empty = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    out = quality.classify(odd(spark), quality.train(odd(spark), empty)).collect()
    assert len(out) == 12 and {r["score"] for r in out} == {0.5}
    one = spark.createDataFrame([(5, 1, 0), (6, None, None), (None, 1, 0), (5, 0, 0)], "doc_id long, quality int, toxic int")
    assert quality.classify(odd(spark), quality.train(odd(spark), one)).count() == 12
    assert quality.classify(nothing(spark), quality.train(nothing(spark), empty)).count() == 0


def test_long_texts_have_the_same_features(monkeypatch):
    rng = random.Random(12)
    text = "\n".join(" ".join(rng.choice(["Word", "zwei", "drei,", "4", "fünf!", "w" + str(rng.randrange(99))]) for _ in range(rng.randrange(12))) for _ in range(300))
    whole = quality.features(pa.array([text]), np.array([3.0]))
    monkeypatch.setattr(kernel, "SEGMENT", 50)
    for a, b in zip(whole, quality.features(pa.array([text]), np.array([3.0])), strict=True):
        assert np.array_equal(a, b)


def test_quality_of_a_text_of_fifty_megabytes():
    import resource

    text = pa.array(["some words of one very long Text 123, " * 1_400_000])
    m = quality.fit([])
    before = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss
    buckets, off, stats = quality.features(text, np.array([np.nan]))
    assert len(quality.scores(m, buckets, off, stats)) == 1 and off[-1] == 8 and stats[0, 0] == np.log1p(11_200_000)
    assert (resource.getrusage(resource.RUSAGE_SELF).ru_maxrss - before) / 1024 < 200


# ---- 7 lines


def test_line_dedup(spark):
    pages = [(i, f"http://User@A.example:80/{i}", f"<html><head><style>p {{}}</style></head><body><nav>Menu</nav><p>Own &amp; only {i}</p><!-- <p>hidden</p> --><div>{'rare' if i < 2 else 'more'}</div></body></html>") for i in range(10)]
    pages += [(20, "http://b.example/", "<p>Menu</p><p>x</p>"), (21, None, None), (22, "", ""), (23, "http://b.example/", "Menu\n\n  x  y "), (24, "nonsense", "<p>q</p>")]
    r = {x["page_id"]: x for x in lines.drop_repeated(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert (r[0]["host"], r[0]["n_lines"], r[0]["n_dropped"], r[0]["kept_text"]) == ("a.example", 3, 1, "Own & only 0\nrare")
    assert (r[5]["n_dropped"], r[5]["kept_text"]) == (2, "Own & only 5")
    assert r[20]["kept_text"] == "Menu\nx" and r[23]["kept_text"] == "Menu\nx y"  # too few pages of that host
    assert (r[21]["n_lines"], r[21]["kept_text"], r[22]["kept_text"], r[24]["host"]) == (0, "", "", "")
    assert lines.drop_repeated(spark.createDataFrame([], "page_id long, url string, html string, host string, pages long, line string")).count() == 0


def test_line_dedup_by_shuffled_join(spark, monkeypatch):
    monkeypatch.setattr(lines, "LINES_BROADCAST", -100)
    test_line_dedup(spark)


# ---- 8 passages


def words(rng, n):
    return ["".join(rng.choice("abcdefghijklmnop") for _ in range(5)) for _ in range(n)]


def pairs_of(spark, texts, **how):
    return passages.shared_passages(docs_of(spark, texts), **how)


def test_passages(spark):
    rng = random.Random(6)
    shared = words(rng, 80)
    fuzzy = [("zz" if i in (20, 45, 61) else w) for i, w in enumerate(shared) if i != 33]
    texts = [
        " ".join(words(rng, 60) + shared + words(rng, 30)), " ".join(words(rng, 5) + fuzzy + words(rng, 90)), " ".join(words(rng, 200)), " ".join(words(rng, 40) + shared[:30] + words(rng, 40)), None, "", " ".join(shared).upper().replace(" ", ", "),
        "same words " * 40, "Same words! " * 40, "few words", "few words",
    ]
    found = pairs_of(spark, texts)
    got = {(r["doc_a"], r["doc_b"]): r for r in found.collect()}
    assert set(got) == {(0, 1), (0, 6), (1, 6), (7, 8)}
    r = got[0, 6]
    assert (r["start_a"], r["words_a"], r["start_b"], r["words_b"], r["similarity"]) == (60, 80, 0, 80, 1.0)
    r = got[0, 1]
    assert (r["start_a"], r["words_a"], r["start_b"], r["words_b"], r["n_equal"]) == (60, 80, 5, 79, 76)
    spans = {r["doc_id"]: (r["start"], r["n_words"], r["partner_id"]) for r in passages.repeated_spans(found).collect()}
    assert spans == {0: (60, 80, 1), 1: (5, 79, 0), 6: (0, 80, 0), 7: (0, 80, 8), 8: (0, 80, 7)}
    assert pairs_of(spark, []).count() == 0 and passages.repeated_spans(pairs_of(spark, [])).count() == 0
    assert {(r["doc_a"], r["doc_b"]) for r in passages.shared_passages(odd(spark)).collect()} == set()
    with pytest.raises(ValueError):
        pairs_of(spark, texts, least_words=10)


@pytest.mark.parametrize("fragment", [10, 19, 30, 45])
@pytest.mark.parametrize("copies", [4, 60])
def test_passages_beside_fragments(spark, fragment, copies):
    """Verbatim passages in documents between others that hold parts of them: every one is found, in rare and in frequent seeds."""
    rng = random.Random(fragment)
    shared, texts, due = [words(rng, 60) for _ in range(12)], [], set()

    def fragments():
        for p in shared:
            for _ in range(3 if copies == 4 else 40):
                at = rng.randrange(60 - fragment + 1)
                texts.append(words(rng, 20) + p[at : at + fragment] + words(rng, 20))

    fragments()
    for p in shared:
        for _ in range(copies):
            due.add(len(texts))
            texts.append(words(rng, rng.randrange(30)) + p + words(rng, rng.randrange(30)))
    fragments()
    got = {r["doc_id"]: r for r in passages.repeated_spans(pairs_of(spark, [" ".join(t) for t in texts])).collect()}
    assert set(got) == due and all(r["n_words"] >= 60 for r in got.values())


@pytest.mark.parametrize(("copies", "share", "least"), [(2, 0.95, 0.9), (2, 0.9, 0.9), (2, 0.85, 0.9), (40, 0.8, 0.9), (100, 0.8, 0.9)])
def test_fuzzy_passages(spark, copies, share, least):
    """Passages of 60 words with scattered edits; in larger groups each text has half of them, so that any two agree in `share`."""
    rng, texts = random.Random(7), []
    for _ in range(40 if copies == 2 else 2):
        shared = words(rng, 60)
        for i in range(copies):
            own = list(shared)
            if copies > 2 or i:
                for j in rng.sample(range(60), round(60 * (1 - share) * (1 if copies == 2 else 0.5))):
                    own[j] = words(rng, 1)[0]
            texts.append(words(rng, 30) + own + words(rng, 30))
    got = {r["doc_id"] for r in passages.repeated_spans(pairs_of(spark, [" ".join(t) for t in texts])).collect()}
    assert len(got) >= least * len(texts)


def test_fuzzy_passages_beside_fragments(spark):
    """Two fuzzy copies whose seeds all lie in words that 40 other documents hold: they meet, whichever those are."""
    rng, texts, due = random.Random(9), [], set()
    for _ in range(8):
        shared = words(rng, 64)
        row, _, _ = passages.sampled(*kernel.word_hashes(*kernel.bytes_of(pa.array([" ".join(shared[18:42])])), kernel.MARKS))
        texts += [words(rng, 70) + shared[18:42] + words(rng, 70) for _ in range(20)]
        own = [words(rng, 1)[0] if i % 5 == 2 and not 18 <= i < 42 else w for i, w in enumerate(shared)]
        if len(row) > 1:
            due |= {len(texts), len(texts) + 1}
        texts += [words(rng, 30) + t + words(rng, 30) for t in (shared, own)]
        texts += [words(rng, 70) + shared[18:42] + words(rng, 70) for _ in range(20)]
    got = {r["doc_id"] for r in passages.repeated_spans(pairs_of(spark, [" ".join(t) for t in texts])).collect()}
    assert len(due) >= 10 and got >= due


def test_large_groups_of_near_copies_take_few_comparisons(spark):
    """Near copies join through few of their pairs, whole stretches are told of each, and each place of a passage that the least document repeats."""
    rng = random.Random(11)
    shared = [words(rng, 200), words(rng, 60)]
    texts = [words(rng, 40) + shared[1] + words(rng, 70) + shared[1] + words(rng, 30)]
    for i in range(120):
        own = list(shared[0])
        for j in rng.sample(range(12, 188), 3):
            own[j] = words(rng, 1)[0]
        texts += [own, words(rng, 20) + shared[1] + words(rng, 20)] if i % 2 else [own]
    found = pairs_of(spark, [" ".join(t) for t in texts]).cache()
    assert found.count() < 120 * 119 / 4  # half of the pairs of near copies
    got = collections.defaultdict(list)
    for r in passages.repeated_spans(found).collect():
        got[r["doc_id"]].append((r["start"], r["n_words"]))
    assert set(got) == set(range(len(texts)))
    assert sorted(p // 10 for p, _ in got[0]) == [4, 17]
    assert all(got[i] == [(0, 200)] for i, t in enumerate(texts) if len(t) == 200)


def test_words_alike():
    rng = np.random.default_rng(3)
    a, b = rng.integers(0, 4, (7, passages.AROUND), dtype=np.uint8), rng.integers(0, 4, (9, passages.AROUND), dtype=np.uint8)
    assert np.array_equal(passages.alike(a, b), ((a[:, None] == b) & (a[:, None] > 0)).sum(axis=2))


def test_alone_fragments_as_columns():
    """Fragments that are aligned together give what each gives by itself."""
    rng = np.random.default_rng(5)
    for _ in range(20):
        a, b = rng.integers(0, 9, 300), rng.integers(0, 9, 280)
        at = rng.integers(0, 150, 2)
        b[at[1] : at[1] + 90] = np.where(rng.random(90) < 0.85, a[at[0] : at[0] + 90], 99)
        first = at + rng.integers(0, 60)
        last = first + rng.integers(5, 20)
        b[first[1] : first[1] + 5], b[last[1] : last[1] + 5] = a[first[0] : first[0] + 5], a[last[0] : last[0] + 5]
        xs, ys, same = passages.columns_of(a, b, np.array([first[0], last[0]]), np.array([first[1], last[1]]))
        due = {(int(xs[p]), int(ys[p]), q - p, int(same[p:q].sum())) for p, q in passages.passages_within(same, 30, 0.8)}
        off = [np.array([0, len(t)]) for t in (a, b)]
        zero = np.zeros(1, dtype=np.int64)
        got = np.concatenate(passages._alone((a, off[0]), (b, off[1]), zero, zero, first[None], last[None], 30, 0.8))
        assert {tuple(r[1:]) for r in got.tolist()} == due


@pytest.mark.parametrize("period", [6, 10, 15])
def test_passages_of_repeated_lines(spark, period):
    rng, texts = random.Random(period), []
    for _ in range(10):
        line = words(rng, period)
        texts += [words(rng, 40) + line * (200 // period) + words(rng, 40) for _ in range(2)]
    got = collections.Counter()
    for r in passages.repeated_spans(pairs_of(spark, [" ".join(t) for t in texts])).collect():
        got[r["doc_id"]] += r["n_words"]
    assert len(got) == len(texts) and min(got.values()) >= 130


def test_passages_of_columns():
    same = np.array([0] * 5 + [1] * 60 + [0] * 9 + [1] * 8 + [0] * 40 + [1, 1, 1, 1, 0] * 12 + [0] * 3, dtype=bool)
    assert passages.passages_within(same, 50, 0.8) == [(5, 82), (122, 181)]
    a = np.arange(100)
    b = np.concatenate([a[:30], [900, 901], a[30:70], [902], a[71:]])
    xs, ys, equal = passages.columns_of(a, b, np.array([10, 25, 30, 60]), np.array([10, 25, 32, 62]))
    assert (len(xs), int(equal.sum()), int(xs[0]), int(ys[-1])) == (102, 99, 0, 101)


def test_every_long_exact_repeat_is_found(spark, sf):
    rows = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()
    import re

    texts = {r["doc_id"]: re.findall(r"[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", r["text"].translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))) for r in rows}
    having = collections.defaultdict(set)
    for d, w in texts.items():
        for p in range(len(w) - 49):
            having[tuple(w[p : p + 50])].add(d)
    covered = collections.defaultdict(set)
    for r in passages.op8_shared_passages(spark, sf).collect():
        covered[r["doc_id"]] |= set(range(r["start"], r["start"] + r["n_words"]))
    assert having
    for d, w in texts.items():
        for p in range(len(w) - 49):
            if len(having[tuple(w[p : p + 50])]) > 1:
                assert set(range(p, p + 50)) <= covered[d]


def test_chains_against_all_chains():
    rng = random.Random(8)
    for _ in range(80):
        n = rng.randint(1, 9)
        first = np.array([[rng.randrange(200), rng.randrange(200)] for _ in range(n)])
        last = first + np.array([[rng.randrange(20)] for _ in range(n)])
        weight, best = np.array([rng.randint(1, 3) for _ in range(n)]), {}
        cost = lambda j, i, first=first, last=last: passages.GAP_COST * float((first[i] - last[j]).sum())

        def score(i, first=first, last=last, weight=weight, n=n, best=best, cost=cost):
            if i not in best:
                best[i] = passages.SEED_SCORE * weight[i] + max([0.0, *(score(j) - cost(j, i) for j in range(n) if (last[j] < first[i]).all())])
            return best[i]

        found = passages.best_chains(first, last, weight)
        assert sorted(i for c in found for i in c) == list(range(n))
        value = lambda c, weight=weight, cost=cost: passages.SEED_SCORE * weight[c].sum() - sum(cost(x, y) for x, y in zip(c, c[1:], strict=False))
        assert np.isclose(max(map(value, found)), max(score(i) for i in range(n)))
        assert all((last[x] < first[y]).all() for c in found for x, y in zip(c, c[1:], strict=False))


def test_fragments_and_chains():
    a, b = np.array([5, 1, 9, 30, 100, 33, 5, 7]), np.array([4, 0, 8, 32, 99, 35, 4, 7])
    row, first, last, seeds = passages.fragments(np.array([0, 0, 0, 0, 0, 0, 0, 1]), a, b)
    assert row.tolist() == [0, 0, 0, 1] and seeds.tolist() == [2, 3, 1, 1]
    assert first.tolist() == [[30, 32], [1, 0], [100, 99], [7, 7]] and last.tolist() == [[33, 35], [9, 8], [100, 99], [7, 7]]
    assert passages.chains(first[:3], last[:3], seeds[:3]) == [[1, 0]]


# ---- 9 near-duplicates


def near(texts, k=2, percent=80):
    sets = {}
    for i, t in enumerate(texts):
        w = (t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
        for c in "\t\n\v\f\r":
            w = w.replace(c, " ")
        w = [x for x in w.split(" ") if x]
        sets[i] = {tuple(w[p : p + k]) for p in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set()
    links = collections.defaultdict(set)
    for i in sets:
        for j in sets:
            if i != j and sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                links[i].add(j)
    return sets, components(sets, links)


def near_texts(rng):
    base = [words(rng, rng.choice([1, 2, 3, 8, 30, 120])) for _ in range(30)]
    texts = [" ".join(b) for b in base]
    for _ in range(120):
        b = list(rng.choice(base))
        for _ in range(rng.randint(0, max(1, len(b) // 12))):
            b[rng.randrange(len(b))] = "new" + str(rng.randrange(99))
        texts.append(rng.choice([" ", "\n", "\t ", "\x0b"]).join(b).upper() if rng.random() < 0.3 else " ".join(b))
    return [*texts, None, "", " \n", "é É", "É É", "a b", "a b", "one", "ONE"]


@pytest.mark.parametrize("k", [2, 5])
def test_near_duplicates_against_brute_force(spark, k, monkeypatch):
    monkeypatch.setattr(neardup, "BLOCK_SETS", 6)
    texts = near_texts(random.Random(9))
    sets, want = near(texts, k)
    got = {r["doc_id"]: r for r in neardup.near_duplicates(docs_of(spark, texts), k=k).collect()}
    for i in sets:
        assert (got[i]["n_shingles"], got[i]["component_id"], got[i]["kept"]) == (len(sets[i]), want[i], want[i] == i), texts[i]


def test_near_duplicates_odd_rows(spark):
    got = neardup.near_duplicates(odd(spark)).collect()
    assert len(got) == 12 and all(r["component_id"] is None and r["kept"] for r in got if r["doc_id"] is None)
    assert {r["component_id"] for r in got if r["doc_id"] in (5, 6)} == {5}
    assert neardup.near_duplicates(nothing(spark)).count() == 0
    one = neardup.keep_one(odd(spark))
    assert one.columns == odd(spark).columns
    assert collections.Counter(r["doc_id"] for r in one.collect()) == collections.Counter([1, 2, 3, 4, 5, 7, 7, 8, 9, None])


def test_words_are_hashed_alike_wherever_they_stand(monkeypatch):
    texts = ["ab  cd\nEF", "", None, "cd", "x ef", "  ab", "w" * 300, ""]
    want = {}
    for segment in (1 << 21, 7, 1):
        monkeypatch.setattr(kernel, "SEGMENT", segment)
        h, off = kernel.word_hashes(*kernel.bytes_of(pa.array(texts)))
        assert list(np.diff(off)) == [3, 0, 0, 1, 2, 1, 1, 0]
        assert h[1] == h[3] and h[2] == h[5] and h[0] == h[6] and len(set(h.tolist())) == 5
        want.setdefault("h", h)
        assert (h == want["h"]).all()
    sliced = pa.array(["zz", *texts]).slice(1)
    assert (kernel.word_hashes(*kernel.bytes_of(sliced))[0] == want["h"]).all()


def test_sketches_fill_and_estimate():
    rng = np.random.default_rng(3)
    sets = [np.sort(rng.choice(np.arange(10**6, dtype=np.uint64), n, replace=False)) for n in (1, 2, 50, 1000)]
    off = np.concatenate([[0], np.cumsum([len(s) for s in sets])])
    s = kernel.sketches(np.concatenate(sets), off, 64)
    assert (s != ~np.uint64(0)).all()
    errors = []
    for _ in range(20):
        u = rng.integers(0, 1 << 63, 900, dtype=np.uint64)
        a, b = u[:800], u[100:]
        t = kernel.sketches(np.concatenate([a, b]), np.array([0, 800, 1600]), 252)
        errors.append((t[0] == t[1]).mean() - 700 / 900)
    assert abs(np.mean(errors)) < 0.02 and np.std(errors) < 0.04


# ---- 10 language


def test_language_of_documents_and_pages(spark, sf):
    rows = language.op10_language(spark, sf).collect()
    assert np.mean([r["declared"] == r["language"] for r in rows]) > 0.97 and np.mean([r["accepted"] for r in rows]) > 0.98
    rows = language.page_language(spark, sf).collect()
    assert np.mean([r["declared"] == r["language"] for r in rows]) > 0.97


def test_language_accuracy_on_rows_kept_from_fitting(spark):
    """Text alone, and all evidence, on documents that no model has seen; declarations are hidden from the texts' model and from the first figure."""
    from pyspark.sql import functions as F

    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    held = F.pmod(F.xxhash64("doc_id"), F.lit(3)) == 0
    truth = {r["doc_id"]: r["lang"] for r in docs.where(held).select("doc_id", "lang").collect()}
    hidden = docs.withColumn("lang", F.when(~held, F.col("lang")))
    for source in ("source", None):
        own = hidden if source else hidden.withColumn("source", F.lit("one"))
        found = {r["key"]: r for r in language.identify(language.of_documents(own)).collect()}
        right = [found[d]["language"] == lang for d, lang in truth.items() if lang]
        assert len(right) > 200 and np.mean(right) > 0.95


def test_language_posteriors_against_numpy(spark, sf):
    """Each posterior again, from the model's table and the counts of hosts, in plain NumPy."""
    import math

    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(200).cache()
    rows = language.of_documents(docs).collect()
    model = language.fit(language.of_documents(docs))
    n = len(model.languages)
    codes = [language._codes(pa.array([r["text"]])) for r in rows]
    scores = np.array([[t[c].sum() for t in model.table] for c, _ in codes])
    grams = np.array([len(c) for c, _ in codes])
    guess = [int(s[:n].argmax()) if g and s[:n].max() > s[n] else None for s, g in zip(scores, grams, strict=True)]
    overall = (np.bincount([g for g in guess if g is not None], minlength=n) + 1.0) / (sum(g is not None for g in guess) + n)
    weight = language.HOST_WEIGHT
    smooth = lambda counts, parent: (counts + weight * parent) / (counts.sum() + weight)
    above = smooth(np.bincount([g for g in guess if g is not None], minlength=n), overall)
    got = {r["key"]: r for r in language.identify(language.of_documents(docs)).collect()}
    for i, r in enumerate(rows):
        own = np.bincount([g for g, x in zip(guess, rows, strict=True) if g is not None and x["host"] == r["host"]], minlength=n)
        prior = smooth(own, above) if own.sum() else overall
        total = scores[i] * min(1.0, language.EVIDENCE / max(1, grams[i])) + np.append(np.log(prior * (1 - language.UNKNOWN)), math.log(language.UNKNOWN))
        said = (r["declared"] or "").lower()
        if said in model.languages:
            wrong = math.log((1 - language.DECLARED_RIGHT) / max(1, n - 1))
            total += np.array([math.log(language.DECLARED_RIGHT) if x == said else wrong for x in model.languages] + [math.log(1 / n)])
        best = int(total.argmax())
        assert got[r["key"]]["language"] == [*model.languages, "und"][best]
        assert np.isclose(got[r["key"]]["posterior"], 1 / np.exp(total - total[best]).sum())


def test_language_evidence(spark):
    en, de = "the and of that with this from there " * 6, "der und die nicht sich ein mit auch " * 6
    rows = [(i, en if i % 2 else de, "en" if i % 2 else "de", None, f"h{i % 2}") for i in range(60)]
    rows += [(100, "a", None, None, "h0"), (101, "a", None, None, "h1"), (102, "a", "de", None, "h9"), (103, "a", "en", None, "h9"), (104, "a", None, "de", "h9"), (105, "123 !!", "en", None, "h1"), (106, None, "en", None, None), (107, "qzxj vvkq wwqz xjqk zzqx", None, None, None), (108, de, "en", None, "h1"), (None, en, None, None, None)]
    df = spark.createDataFrame(rows, "key long, text string, declared string, suffix string, host string")
    r = {x["key"]: x for x in language.identify(df).collect()}
    assert len(r) == len(rows)
    assert (r[100]["language"], r[101]["language"], r[102]["language"], r[103]["language"], r[104]["language"]) == ("de", "en", "de", "en", "de")
    assert (r[105]["language"], r[105]["accepted"], r[106]["language"]) == ("und", False, "und")
    assert r[107]["language"] == "und" and r[108]["language"] == "de" and r[None]["language"] == "en"
    assert all(r[i]["language"] == ("en" if i % 2 else "de") for i in range(60))
    assert language.identify(df.where("false")).count() == 0
    kept = language.keep_identified(odd(spark))
    assert kept.columns == odd(spark).columns


def test_rare_languages_and_many_are_known(spark):
    rng = random.Random(12)
    speech = [words(rng, 40) for _ in range(70)]
    text = lambda i: " ".join(rng.choice(speech[i]) for _ in range(60))
    rows = [(i, text(0), "l0", None, "h") for i in range(9_000)] + [(10_000 + i, text(1), "l1", None, "h") for i in range(6)]
    df = spark.createDataFrame(rows, "key long, text string, declared string, suffix string, host string")
    assert language.fit(df).languages == ("l0", "l1")
    assert {r["language"] for r in language.identify(df).where("key >= 10000").collect()} == {"l1"}
    many = spark.createDataFrame([(10 * i + j, text(i), f"l{i}", None, f"h{i}") for i in range(70) for j in range(6)], df.schema)
    assert len(language.fit(many).languages) == 70


# ---- all


def test_nothing_else_imports_this_package():
    import pathlib
    import re

    root = pathlib.Path(__file__).resolve().parents[2]
    for p in [*root.glob("regpath/**/*.py"), *root.glob("*.py"), *root.glob("tests/*.py")]:
        if "llm" not in p.relative_to(root).parts and p.name not in ("__spark_entry__.py", "corpus_pipeline.py"):
            assert not re.search(r"regpath\.llm|import corpus_pipeline", p.read_text()), p
