"""Embeddings and fingerprints against brute force."""

import random

import numpy as np
import pytest
import xxhash

from xlsql.llm import embeddings, graph, simhash


def components(n, links):
    up = list(range(n))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for a, b in links:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    return [find(i) for i in range(n)]


@pytest.mark.parametrize("one_task", [0, 10**6])
def test_connected_components_of_chains_stars_and_rings(spark, monkeypatch, one_task):
    monkeypatch.setattr(graph, "ONE_TASK", one_task)
    monkeypatch.setattr(graph, "HOT_ROWS", 50)
    rng = random.Random(3)
    links = [(i, i + 1) for i in range(0, 60)] + [(100, k) for k in range(101, 400)] + [(500 + i, 500 + (i + 1) % 20) for i in range(20)] + [(rng.randrange(600, 900), rng.randrange(600, 900)) for _ in range(150)]
    df = spark.createDataFrame([*links, (7, 7), (None, 3)], "a long, b long").repartition(7)
    got = {r["node"]: r["component"] for r in graph.connected_components(df).collect()}
    want = components(900, links)
    assert got == {n: want[n] for n in {x for a, b in links if a != b for x in (a, b)}}


def test_components_of_nothing(spark):
    assert graph.connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def brute_cosine(rows, cosine=0.95):
    good = [(i, np.array(v, float)) for i, v in rows if v is not None and len(v) and all(x is not None and np.isfinite(x) for x in v) and any(v)]
    at = {k: i for i, k in enumerate(range(len(rows)))}
    links, n = [], [0] * len(rows)
    pos = [k for k, (i, v) in enumerate(rows) if any(v is g or (v is not None and i == gi and np.array_equal(v, g)) for gi, g in good if v is not None and None not in v)]
    for x in range(len(pos)):
        for y in range(x + 1, len(pos)):
            a, b = np.array(rows[pos[x]][1], float), np.array(rows[pos[y]][1], float)
            if len(a) == len(b) and a @ b / np.linalg.norm(a) / np.linalg.norm(b) >= cosine:
                links.append((pos[x], pos[y]))
                n[pos[x]] += 1
                n[pos[y]] += 1
    assert at is not None
    return n, components(len(rows), links)


def test_cosine_groups_match_brute_force(spark, monkeypatch):
    monkeypatch.setattr(embeddings, "HOME_BLOCK", 40)
    monkeypatch.setattr(embeddings, "GUEST_BLOCK", 60)
    rng = np.random.default_rng(5)
    base = rng.normal(size=(12, 8))
    rows = [(int(k), (base[k % 12] + rng.normal(size=8) * 0.12 * (k % 5)).tolist()) for k in range(360)]
    rows += [(1000 + k, base[0].tolist()) for k in range(30)] + [(2000, None), (2001, [0.0] * 8), (2002, [float("nan")] * 8), (2003, [1.0, None, *[0.0] * 6]), (2004, []), (2005, [1.0, 0.0]), (2006, [2.0, 0.01])]
    df = spark.createDataFrame([(i, v, "x", 5) for i, v in rows], "vec_id long, embedding array<double>, rep string, n_links int").repartition(5)
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in embeddings.cosine_groups(df).collect()}
    n, comp = brute_cosine(rows)
    assert got == {rows[k][0]: (n[k], rows[comp[k]][0], comp[k] == k) for k in range(len(rows))}


@pytest.mark.parametrize("kind", ["float", "double"])
def test_multiples_of_one_vector_over_many_pivots(spark, monkeypatch, kind):
    """Parallel pivots are one; vectors that differ only by rounding meet whatever cell they are put in."""
    monkeypatch.setattr(embeddings, "HOME_BLOCK", 12)
    monkeypatch.setattr(embeddings, "GUEST_BLOCK", 30)
    rng = np.random.default_rng(8)
    base = rng.normal(size=(4, 16))
    rows = [(k, (base[k % 4] * rng.uniform(1e-3, 1e3) * (1 + 1e-7 * rng.normal(size=16))).astype("f4" if kind == "float" else "f8").tolist()) for k in range(240)]
    df = spark.createDataFrame(rows, f"vec_id long, embedding array<{kind}>").repartition(4)
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embeddings.cosine_groups(df).collect()}
    n, comp = brute_cosine(rows)
    assert got == {k: (n[k], comp[k]) for k in range(240)} and all(x == 59 for x in n)


def test_guest_cells_lose_no_link():
    """Every vector within reach is at home in the cell itself or in one that gets the vector as guest, whatever the pivots."""
    rng = np.random.default_rng(4)
    reach = np.sqrt(2 - 2 * 0.95) + 1e-9
    spared = total = 0
    for _ in range(60):
        dim = int(rng.integers(2, 24))
        table = embeddings.distinct_directions(embeddings._unit(rng.normal(size=(40, dim)) * rng.choice([1, 1, 1e-9], size=(40, 1)) + rng.normal(size=(1, dim)) * rng.choice([0, 3])))
        x = embeddings._unit(np.concatenate([table, rng.normal(size=(120, dim)), table[:10] + 1e-9 * rng.normal(size=(len(table[:10]), dim))]))
        y = embeddings._unit(x + rng.normal(size=x.shape) * 0.3 / np.sqrt(dim))
        home, near = embeddings.guest_cells(x, table, reach)
        other, _ = embeddings.guest_cells(y, table, reach)
        linked = (x * y).sum(1) >= 0.95
        assert near[np.flatnonzero(linked), other[linked]].all() or ((home == other) | near[np.arange(len(x)), other])[linked].all()
        spared, total = spared + (~near).sum(), total + near.size
    assert spared / total > 0.2


def test_cell_report_tells_guests(spark):
    rng = np.random.default_rng(3)
    rows = [(k, rng.normal(size=3).tolist()) for k in range(400)]
    report = embeddings.cell_report(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    assert sum(r["homes"] for r in report) == 400 and sum(r["guests"] for r in report) < 400 * 3


def test_hot_groups_meet_by_broadcast(spark, monkeypatch):
    from pyspark.sql import functions as F

    monkeypatch.setattr(graph, "HOT_ROWS", 5)
    rows = spark.createDataFrame([(i, 0 if i < 300 else i % 50) for i in range(600)], "id long, k long")
    groups = rows.groupBy("k").agg(F.count("*").alias("copies"), F.min("id").alias("first"))
    assert sorted(map(tuple, graph.join_groups(rows, groups, ["k"]).select("id", "first").collect())) == sorted((i, 0 if i < 300 or i % 50 == 0 else 300 + (i % 50)) for i in range(600))


def test_cosine_groups_of_an_empty_table(spark):
    assert embeddings.cosine_groups(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def plain_fingerprint(text):
    words = [w for w in __import__("re").split("[\x20\x09-\x0d]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")) if w]
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] if len(words) >= 3 else [" ".join(words)] if words else []
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


@pytest.mark.parametrize("text", [None, "", " \t\n", "One", "One two", "A b C d e A b C", "é È ß   x y", "x " * 300])
def test_fingerprint(text):
    assert simhash.fingerprint(text) == plain_fingerprint(text)


def test_bit_groups_cover_every_close_pair():
    rng = random.Random(1)
    for n in (0, 10**5, 10**9, 10**11):
        masks = simhash.bit_groups(3, n)
        assert all(m.bit_count() >= min(20, n.bit_length()) for m in masks)
        for _ in range(500):
            x = rng.getrandbits(64)
            y = x
            for b in rng.sample(range(64), 3):
                y ^= 1 << b
            assert any(x & m == y & m for m in masks)


def brute_groups(rows, distance=3):
    prints = [plain_fingerprint(t) for _, t in rows]
    links = [(i, j) for i in range(len(rows)) for j in range(i + 1, len(rows)) if (prints[i] ^ prints[j]).bit_count() <= distance]
    return prints, components(len(rows), links)


def corpus(n=150, seed=2):
    rng = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(60)]
    texts = [" ".join(rng.choice(vocabulary) for _ in range(rng.randrange(0, 120))) for _ in range(n)]
    for k in range(n):
        words = texts[rng.randrange(n)].split()
        if words:
            words[rng.randrange(len(words))] = "Changed"
        texts.append(" ".join(words))
    return [(i, t) for i, t in enumerate([*texts, None, "", " ", "same text here", "Same TEXT here"])]


def test_simhash_groups_match_brute_force(spark, monkeypatch):
    rows = corpus()
    df = spark.createDataFrame([(i, t, 1, "x") for i, t in rows], "doc_id long, text string, fp int, component_id string").repartition(6)
    prints, comp = brute_groups(rows)
    want = {i: (f"{prints[i]:016x}", comp[i]) for i, _ in rows}
    assert {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in simhash.simhash_groups(df).collect()} == want
    # a fingerprint that only documents without id have
    lone = df.select("doc_id", "text").unionByName(spark.createDataFrame([(None, rows[40][1] + " tail"), (None, rows[40][1])], "doc_id long, text string"))
    again = [r for r in simhash.simhash_groups(lone).collect()]
    assert {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in again if r["doc_id"] is not None} == want
    # all buckets through the block path, cut small
    monkeypatch.setattr(simhash, "LIGHT", 1)
    monkeypatch.setattr(simhash, "BLOCK", 3)
    assert simhash.simhash_groups(lone).count() == len(rows) + 2
    assert {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in simhash.simhash_groups(df).collect()} == want


def test_dedup_keep_keeps_one_of_each_group_and_all_columns(spark):
    rows = [(1, "a b c d", "x"), (2, "A B C D", "y"), (3, "other words entirely here", "z"), (3, "other words entirely here", "z"), (None, "a b c d", "n")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    kept = simhash.dedup_keep(df)
    assert kept.columns == df.columns
    assert sorted(map(tuple, kept.collect()), key=str) == sorted([rows[0], rows[2], rows[4]], key=str)


def test_dedup_keep_is_the_same_whatever_the_partitions(spark):
    rows = [(1, f"text number {i % 3} of one document", i, "c") for i in range(40)] + [(2, None, 1, "c"), (2, None, 1, "c")]
    df = spark.createDataFrame(rows, "doc_id long, text string, _kept_id int, _all string")
    first = {str(sorted(map(tuple, simhash.dedup_keep(df.repartition(n)).collect()))) for n in (1, 3, 8)}
    assert len(first) == 1 and simhash.dedup_keep(df).columns == df.columns


def test_table_of_distances_discards_pairs(spark):
    r = simhash.pair_report(spark.createDataFrame(corpus(300), "doc_id long, text string")).first()
    assert r["met"] >= r["passed"] >= r["linked"] > 0


def test_registered_simhash_query_matches_brute_force(spark):
    from xlsql.llm.registry import op3_simhash_near_dedup
    from xlsql.session import load_table

    sf = "/root/testdata/sf0.001"
    rows = [(r["doc_id"], r["text"]) for r in load_table(spark, sf, "documents").select("doc_id", "text").orderBy("doc_id").collect()]
    prints, comp = brute_groups(rows)
    assert {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in op3_simhash_near_dedup(spark, sf).collect()} == {rows[k][0]: (f"{prints[k]:016x}", rows[comp[k]][0]) for k in range(len(rows))}


def test_simhash_of_an_empty_table(spark):
    assert simhash.simhash_groups(spark.createDataFrame([], "doc_id long, text string")).count() == 0
