import numpy as np

from metricblock.llm.embedding_dedup import link_vectors, op5_sorted_passes, small_vectors
from metricblock.llm.neighbours import chi_square_point, found_by_cells, op2_projection_tree, search

SCHEMA = "vec_id long, embedding array<float>, label int, width int, id long"


def table(spark, rows):
    return spark.createDataFrame([(*r, 9, 9) for r in rows], SCHEMA)


def clustered(n=600, seed=3):
    rng = np.random.default_rng(seed)
    centres = rng.standard_normal((12, 16))
    x = centres[rng.integers(0, 12, n)] + rng.standard_normal((n, 16)) * rng.choice([0.05, 0.2, 0.8], n)[:, None]
    x[::50] = x[1]
    return x.astype(np.float32), rng.integers(0, 3, n)


def brute_links(ids, x, label, threshold=0.93):
    u = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    g = (u @ u.T >= threshold) & (label[:, None] == label[None, :])
    np.fill_diagonal(g, False)
    comp = np.array(ids)
    while True:
        new = np.array([min([comp[i], *comp[g[i]]]) for i in range(len(ids))])
        if (new == comp).all():
            return g.sum(axis=1), comp
        comp = new


def test_links_against_brute_force(spark):
    x, label = clustered()
    rows = {r["vec_id"]: r for r in link_vectors(table(spark, [(i, v.tolist(), int(c)) for i, (v, c) in enumerate(zip(x, label, strict=True))])).collect()}
    links, comp = brute_links(range(len(x)), x, label)
    got = np.array([rows[i]["n_links"] for i in range(len(x))])
    assert (got <= links).all() and got.sum() >= 0.97 * links.sum()
    assert np.mean([rows[i]["component_id"] == comp[i] for i in range(len(x))]) > 0.97
    assert all(r["kept"] == (r["vec_id"] == r["component_id"]) for r in rows.values())


def test_links_where_a_label_shares_a_direction(spark):
    rng = np.random.default_rng(8)
    x = rng.standard_normal((2000, 32)) + 2.2 * np.sqrt(32) * np.eye(32)[0]  # cosines of about 0.83
    near = x[:400] + 0.4 * rng.standard_normal((400, 32))
    x = np.concatenate([x, near]).astype(np.float32)
    label = np.zeros(len(x), dtype=int)
    rows = {r["vec_id"]: r for r in link_vectors(table(spark, [(i, v.tolist(), 0) for i, v in enumerate(x)])).collect()}
    links, comp = brute_links(range(len(x)), x, label)
    got = np.array([rows[i]["n_links"] for i in range(len(x))])
    assert links.sum() >= 800 and (got <= links).all() and got.sum() >= 0.97 * links.sum()


def test_small_vectors_lose_no_more_than_they_say():
    x = np.random.default_rng(1).standard_normal((50, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    small, scale, lost = small_vectors(x)
    y = small * scale[:, None]
    assert (np.abs(x @ x.T - y @ y.T) <= (lost[:, None] + lost[None, :]) * 1.01 + 1e-9).all() and lost.max() < 0.01


def from_table(spark, d):
    rows = sorted((r["vec_id"], r["embedding"], r["label"]) for r in spark.read.parquet(f"{d}/embeddings.parquet").collect())
    return [r[0] for r in rows], np.array([r[1] for r in rows]), np.array([r[2] for r in rows])


def test_op5_over_the_table_against_brute_force(spark, sf):
    ids, x, label = from_table(spark, sf)
    links, comp = brute_links(ids, x, label)
    rows = sorted((r["vec_id"], r["n_links"], r["component_id"]) for r in op5_sorted_passes(spark, sf).collect())
    assert rows == list(zip(ids, links.tolist(), comp.tolist(), strict=True))


BAD = [(1, None, 1), (2, [0.0, 0.0], 1), (3, [1.0, None], 1), (4, [float("nan"), 1.0], 1), (5, [float("inf"), 1.0], 1), (6, [1.0, 0.0], None), (7, [], 1)]
GOOD = [(10, [1.0, 0.0], 1), (11, [2.0, 0.0], 1), (12, [1.0, 0.0], 1), (12, [1.0, 0.0], 1), (13, [1.0, 0.0], 2), (14, [1.0, 0.0, 0.0], 1)]


def test_links_of_odd_rows(spark):
    rows = [(r["vec_id"], r["n_links"], r["component_id"], r["kept"]) for r in link_vectors(table(spark, BAD + GOOD)).collect()]
    assert all((i, 0, i, True) in rows for i in (1, 2, 3, 4, 5, 6, 7, 13, 14))
    assert sorted(r for r in rows if r[0] in (10, 11, 12)) == [(10, 3, 10, True), (11, 3, 10, False), (12, 3, 10, False), (12, 3, 10, False)]
    assert link_vectors(table(spark, [])).count() == 0


def brute_knn(x, queries, k=10):
    d = np.sqrt(((x[:, None, :].astype(float) - x[None].astype(float)) ** 2).sum(-1))
    np.fill_diagonal(d, np.inf)
    return {q: np.lexsort((np.arange(len(x)), d[q]))[:k].tolist() for q in queries}


def test_search_recall(spark):
    x, label = clustered(900)
    t = table(spark, [(i, v.tolist(), int(c)) for i, (v, c) in enumerate(zip(x, label, strict=True))])
    rows = search(t, t.where("vec_id % 10 = 0")).collect()
    true = brute_knn(x, range(0, 900, 10))
    found = {}
    for r in sorted(rows, key=lambda r: (r["query_id"], r["rank"])):
        found.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    assert sum(len(set(true[q]) & {v for v, _ in found[q]}) for q in true) >= 0.97 * 10 * len(true)
    for q, near in found.items():
        assert [s for _, s in near] == sorted(s for _, s in near)
        assert all(abs(s - np.sqrt(((x[q].astype(float) - x[v].astype(float)) ** 2).sum())) < 1e-12 for v, s in near)


def test_op2_over_the_table_against_brute_force(spark, sf):
    ids, x, _ = from_table(spark, sf)
    place = {i: n for n, i in enumerate(ids)}
    true = brute_knn(x, [place[i] for i in ids if i % 100 == 0])
    rows = op2_projection_tree(spark, sf).collect()
    found = {q: {place[r["vec_id"]] for r in rows if place[r["query_id"]] == q} for q in true}
    assert len(rows) == 10 * len(true) and sum(len(set(true[q]) & found[q]) for q in true) >= 0.9 * len(rows)
    assert all(abs(r["score"] - np.linalg.norm(x[place[r["query_id"]]].astype(float) - x[place[r["vec_id"]]].astype(float))) < 1e-12 for r in rows)


def test_search_verifies_few_where_neighbours_are_near(spark):
    rng = np.random.default_rng(6)
    x = np.repeat(rng.standard_normal((150, 32)), 30, axis=0) + 0.15 * rng.standard_normal((4500, 32))
    t = table(spark, [(i, v.tolist(), 0) for i, v in enumerate(x.astype(np.float32))])
    asked = t.where("vec_id % 100 = 0")
    parts = found_by_cells(t, asked).select("query_id", "verified").groupBy("query_id", "verified").count().groupBy("query_id").sum("verified").collect()
    assert np.mean([r[1] for r in parts]) < 0.1 * len(x)
    true = brute_knn(x.astype(np.float32), range(0, 4500, 100))
    found = {}
    for r in search(t, asked).collect():
        found.setdefault(r["query_id"], set()).add(r["vec_id"])
    assert sum(len(set(true[q]) & found[q]) for q in true) >= 0.97 * 10 * len(true)


def test_search_of_odd_rows(spark):
    t = table(spark, BAD + GOOD[:3] + GOOD[5:])
    rows = sorted((r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in search(t, t).collect())
    assert rows == [(6, 1, 10, 0.0), (6, 2, 12, 0.0), (6, 3, 11, 1.0), (10, 1, 6, 0.0), (10, 2, 12, 0.0), (10, 3, 11, 1.0), (11, 1, 6, 1.0), (11, 2, 10, 1.0), (11, 3, 12, 1.0), (12, 1, 6, 0.0), (12, 2, 10, 0.0), (12, 3, 11, 1.0)]
    assert search(table(spark, []), t).count() == 0 and search(t, table(spark, [])).count() == 0


def test_chi_square_points():
    assert abs(chi_square_point(0.95, 8) - 15.507) < 1e-3 and abs(chi_square_point(0.99, 2) - 9.2103) < 1e-3
