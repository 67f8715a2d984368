"""N-gram join and nearest neighbours against brute force; and their defined cases."""

import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest

from blockdelta.llm import ann, components, ngram_join
from blockdelta.llm.shingles import shingle_sets


def brute(rows):
    sets = []
    for _, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m.group().lower(), t or ""))
        sets.append({tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
    parent = list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    holders = defaultdict(list)
    for i, s in enumerate(sets):
        for g in s:
            holders[g].append(i)
    for i, s in enumerate(sets):
        for j, n in Counter(j for g in s for j in holders[g] if j > i).items():
            if 100 * n >= 80 * (len(s) + len(sets[j]) - n):
                parent[find(i)] = find(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        least[find(i)] = min(least.get(find(i), d), d)
    return sorted((d, len(sets[i]), least[find(i)]) for i, (d, _) in enumerate(rows))


def fixture():
    rng, rows = random.Random(3), []
    words = [f"w{i}" for i in range(3000)]
    for n, size in ((45, 120), (25, 60), (3, 7), (12, 200)):
        base = [rng.choice(words) for _ in range(size)]
        for k in range(n):
            w = list(base)
            for _ in range(rng.choice([0, 1, 1, 2, size // 30])):
                w[rng.randrange(size)] = rng.choice(words)
            rows.append((" ".join(w).upper() if k % 5 == 0 else "\t ".join(w)))
    common = [rng.choice(words) for _ in range(30)]
    rows += [" ".join(common[: rng.randrange(5, 30)] + [rng.choice(words) for _ in range(rng.randrange(0, 9))]) for _ in range(40)]
    rows += [" ".join(common[: k + 1]) for k in range(30)]
    rows += [None, "", "a b", "A\tb", "   ", "É x", "é x", "long " * 30_000, "long " * 30_001]
    rng.shuffle(rows)
    return list(enumerate(rows))


def test_join(spark):
    rows = fixture()
    df = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, n long").repartition(5)
    got = sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in ngram_join.near_duplicates(df).collect())
    assert got == brute(rows)
    assert ngram_join.near_duplicates(df.limit(0)).count() == 0


def test_every_link_is_counted(spark, monkeypatch):
    """A pair that others connect already is a link all the same; components of several blocks lose none."""
    monkeypatch.setattr(ngram_join, "BLOCK_CLASSES", 8)
    rows = fixture()
    sets = {i: s for (i, _), s in zip(rows, shingle_sets([t for _, t in rows]))}
    classes = {s.tobytes(): set(s.tolist()) for s in sets.values() if len(s)}
    links = {k: sum(100 * len(x & y) >= 80 * len(x | y) for y in classes.values()) - 1 for k, x in classes.items()}
    assert sum(links.values()) > 600
    got = ngram_join.near_duplicates(spark.createDataFrame(rows + [rows[3]], "doc_id long, text string").repartition(5)).collect()
    assert len(got) == len(rows) + 1
    assert all(r["n_links"] == links.get(sets[r["doc_id"]].tobytes(), 0) for r in got)


def test_links_as_pairs(spark, monkeypatch):
    """The pairs themselves: each once, a below b, and as many at each class as the counts say."""
    monkeypatch.setattr(ngram_join, "BLOCK_CLASSES", 8)
    docs, t = spark.createDataFrame(fixture(), "doc_id long, text string").repartition(5), ngram_join.Fraction(4, 5)
    _, classes, parts = ngram_join.join_classes(docs, t, "doc_id", "text")
    pairs = [tuple(r) for r in ngram_join.all_links(docs, classes, parts, t, "doc_id", "text").collect()]
    assert len(set(pairs)) == len(pairs) > 300 and all(a < b for a, b in pairs)
    counted = {r["end"]: r["n_links"] for r in ngram_join.link_counts(docs, classes, parts, t, "doc_id", "text").collect()}
    assert counted == Counter(c for pair in pairs for c in pair)


def test_common_counts():
    rng = np.random.default_rng(7)
    sets = [np.unique(rng.integers(0, 60, 30)) for _ in range(25)] + [np.unique(rng.integers(0, 10**6, 40)) for _ in range(5)]
    got = ngram_join._common(np.repeat(np.arange(30), [len(s) for s in sets]), np.concatenate(sets), 30)
    assert all(got[a, b] == len(np.intersect1d(sets[a], sets[b])) for a in range(30) for b in range(a + 1, 30))


def test_repeated_rows_and_null_ids(spark):
    rows = [(5, "a b c d e f"), (5, "a b c d e f"), (None, "a b c d e f"), (9, None), (None, None)]
    got = ngram_join.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted((r["doc_id"] or -1, r["n_shingles"], r["component_id"] if r["component_id"] is not None else -1) for r in got) == [(-1, 0, -1), (-1, 2, 5), (5, 2, 5), (5, 2, 5), (9, 0, 9)]


def test_crowded_shingle_of_different_texts(spark):
    """Texts that share rare shingles without being similar: all pairs across components are still looked at."""
    rng = random.Random(8)
    core = [f"c{i}" for i in range(40)]
    rows = []
    for k in range(30):
        w = list(core)
        for _ in range(4):
            w[rng.randrange(40)] = f"u{rng.random()}"
        rows.append((k, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in ngram_join.near_duplicates(df).collect())
    assert got == brute(rows)


def test_long_texts_hash_in_pieces():
    text = "".join(random.Random(2).choice("ab c\n") for _ in range(1_500_000)) + " tail of it all now"
    (whole,) = shingle_sets([text])
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    assert len(whole) == len({tuple(words[k : k + 5]) for k in range(len(words) - 4)})
    (a, b) = shingle_sets(["x " + "y" * 2_000_000, "x " + "y" * 2_000_001])
    assert len(a) == 1 and a[0] != b[0]


def test_bound_holds():
    rng = np.random.default_rng(1)
    for n in (1, 3, 50, 4000):
        x, y = (np.unique(rng.integers(0, 1 << 64, n, dtype=np.uint64)) for _ in range(2))
        y = np.unique(np.concatenate([x[: n // 2], y]))
        assert ngram_join.intersection_bound(ngram_join.range_counts(x), ngram_join.range_counts(y))[0] >= len(np.intersect1d(x, y))


def test_components(spark):
    edges = [(k, k + 1) for k in range(0, 60)] + [(100, 200), (200, 300), (7, 7)] + [(500, 500 + k) for k in range(1, 40)]
    got = {r["node"]: r["component"] for r in components.connected(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[k] == 0 for k in range(61)) and got[300] == 100 and all(got[500 + k] == 500 for k in range(40))
    assert components.connected(spark.createDataFrame([], "a long, b long")).count() == 0


def nearest(rows, k):
    good = [(i, np.array(v, float)) for i, v in rows if i is not None and v is not None and None not in v and np.isfinite(v).all() and np.any(v)]
    out = {}
    for i, v in good:
        if i % 50 == 0:
            scored = sorted((-float(v @ w / np.sqrt((v @ v) * (w @ w))), j) for j, w in good if j != i)
            out[i] = scored[:k]
    return out


@pytest.mark.parametrize("shard_rows", [4096, 64])
def test_neighbours(spark, shard_rows):
    rng = np.random.default_rng(5)
    rows = [(i, rng.normal(size=8).astype(np.float32).tolist()) for i in range(400)]
    rows += [(1000 + i, rows[3][1]) for i in range(30)] + [(3000, rows[3][1])]
    rows += [(2000, None), (2050, [0.0] * 8), (2100, [float("nan")] + [1.0] * 7), (2150, [None] + [1.0] * 7), (2200, [float("inf")] + [1.0] * 7), (None, [1.0] * 8)]
    df = spark.createDataFrame([(i, v, 0.5) for i, v in rows], "vec_id long, embedding array<float>, score double").repartition(3)
    got = defaultdict(list)
    for r in ann.nearest(df, df["vec_id"] % 50 == 0, shard_rows=shard_rows).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((-r["score"], r["vec_id"]))
    want = nearest(rows, 5)
    assert set(got) == set(want)
    hits = sum(len({j for _, j in got[q]} & {j for _, j in want[q]}) for q in want)
    assert hits >= 0.95 * sum(map(len, want.values()))
    assert [j for _, j in got[3000]] == [3, 1000, 1001, 1002, 1003]
    for q in got:
        scores = [s for s, _ in got[q]]
        assert scores == sorted(scores)


def test_few_and_no_vectors(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0]), (1, [1.0, 1.0])], "vec_id long, embedding array<float>")
    (only,) = ann.nearest(df, df["vec_id"] % 50 == 0).collect()
    assert (only["query_id"], only["rank"], only["vec_id"]) == (0, 1, 1) and only["score"] == pytest.approx(0.5**0.5)
    assert ann.nearest(df.limit(0), df["vec_id"] % 50 == 0).count() == 0


def test_nearest_ties_and_repeated_ids(spark):
    rng = np.random.default_rng(5)
    rows = [(k, (rng.normal(size=8)).tolist()) for k in range(200) if k not in (50, 60)]
    same = [3.0, 1.0, -2.0, 0.5, 0.0, 1.0, 1.0, 4.0]
    rows += [(50, same)] * 10 + [(60, same)]
    parallel = rng.normal(size=8)
    rows += [(400 + k, (parallel * (k + 1)).tolist()) for k in range(300)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(3)
    for shard_rows in (180, 5000):
        got = {}
        for r in ann.nearest(df, df["vec_id"].isin(50, 400, 410), shard_rows=shard_rows).collect():
            got.setdefault(r["query_id"], {})[r["rank"]] = (r["vec_id"], r["score"])
        assert got[50][1] == (60, pytest.approx(1.0)) and 50 not in {v for v, _ in got[50].values()}
        assert [got[400][k][0] for k in range(1, 6)] == [401, 402, 403, 404, 405]
        assert [got[410][k][0] for k in range(1, 6)] == [400, 401, 402, 403, 404]


def test_recall_on_the_given_table(spark):
    """Over several shards, against all products."""
    df = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet").select("vec_id", "embedding")
    rows = [(r["vec_id"], np.array(r["embedding"], float)) for r in df.where(ann.usable(df["embedding"])).collect()]
    ids, vectors = np.array([k for k, _ in rows]), np.stack([v for _, v in rows])
    unit = vectors / np.linalg.norm(vectors, axis=1, keepdims=True)
    found = {}
    for r in ann.nearest(df, df["vec_id"] % 50 == 0, shard_rows=600).collect():
        found.setdefault(r["query_id"], set()).add(r["vec_id"])
    hits = total = 0
    for q in np.flatnonzero(ids % 50 == 0):
        sims = unit @ unit[q]
        sims[ids == ids[q]] = -np.inf
        best = set(ids[np.lexsort((ids, -sims))[:5]].tolist())
        hits, total = hits + len(best & found[ids[q]]), total + len(best)
    assert total >= 5 * 30 and hits / total >= 0.95


def test_visits_grow_slowly():
    rng = np.random.default_rng(6)
    scored = []
    for n in (1500, 12000):
        vectors = rng.normal(size=(n, 12))
        graph = ann.Graph(**ann.build_graph(np.arange(n)[:, None], vectors))
        names, _ = graph.nearest(np.arange(0, n, 50), vectors[::50], 5, 64)
        unit = vectors / np.linalg.norm(vectors, axis=1, keepdims=True)
        sims = unit[::50] @ unit.T
        sims[np.arange(len(sims)), np.arange(0, n, 50)] = -1
        best = np.argsort(-sims, axis=1)[:, :5]
        assert np.mean([len(set(a) & set(b)) / 5 for a, b in zip(names.tolist(), best.tolist())]) >= 0.9
        scored.append(graph.scored / len(names))
    assert scored[1] < 2.5 * scored[0] and scored[1] < 0.2 * 12000
