"""Vector operators and URL verdicts against brute force; the pipeline as a whole."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from webtraverse.llm import components, embedding_dedup, hash_forest, quality, queries, substring_dedup, url_filter
from webtraverse.llm.minhash_dedup import near_duplicates


def vectors(spark, rows):
    return spark.createDataFrame([(i, v, l, 1, "k") for i, v, l in rows], "vec_id long, embedding array<float>, label int, rep int, key string")


@pytest.fixture(scope="module")
def cloud():
    rng = np.random.default_rng(8)
    rows = []
    for c in range(30):
        centre = rng.standard_normal(12)
        for j in range(rng.integers(1, 25)):
            rows.append((len(rows), (centre + rng.standard_normal(12) * 0.09).astype(np.float32).tolist(), int(c % 3)))
    n = len(rows)
    rows += [(n + i, rows[5][1], rows[5][2]) for i in range(40)]
    rows += [(900, None, 1), (901, [0.0] * 12, 1), (902, [float("nan")] + [1.0] * 11, 1), (903, [float("inf")] + [1.0] * 11, 1), (904, [1.0, 2.0], 1), (905, [1.0, 2.0], 1), (906, [], 1), (907, rows[0][1], None), (908, [3.0], 2)]
    return rows


def usable(v):
    return bool(v) and all(np.isfinite(v)) and any(v)


def test_embedding_groups(spark, cloud):
    good = [(i, np.array(v, dtype=np.float64), l) for i, v, l in cloud if usable(v) and l is not None]
    links = {i: set() for i, _, _ in cloud}
    for i, v, l in good:
        for j, w, m in good:
            if i != j and l == m and len(v) == len(w) and v @ w / np.linalg.norm(v) / np.linalg.norm(w) >= 0.98:
                links[i].add(j)
    got = {r["vec_id"]: r for r in embedding_dedup.near_duplicates(vectors(spark, cloud)).collect()}
    assert {i: r["n_links"] for i, r in got.items()} == {i: len(x) for i, x in links.items()}
    for i in links:
        seen, todo = {i}, [i]
        while todo:
            new = links[todo.pop()] - seen
            seen |= new
            todo += new
        assert got[i]["component_id"] == min(seen) and got[i]["kept"] == (i == min(seen))
    assert embedding_dedup.near_duplicates(vectors(spark, cloud).limit(0)).count() == 0


def test_region_bounds_never_exceed_true_distances():
    rng = np.random.default_rng(1)
    c, x = rng.standard_normal((17, 5)), rng.standard_normal((200, 5))
    c[3] = c[2]
    near, bound = embedding_dedup.region_bounds(x, c)
    for i in range(200):
        d = ((x - x[i]) ** 2).sum(1)
        assert (bound[i][near] <= d + 1e-9).all()


def test_multi_sequence_visits_cells_in_order_and_all_within_reach():
    rng = np.random.default_rng(3)
    for _ in range(60):
        a, b = (np.round(rng.random(rng.integers(1, 9)), 1) for _ in "ab")
        got = list(embedding_dedup.multi_sequence(a, b, 0.9))
        assert {(i, j) for i, j, _ in got} == {(i, j) for i in range(len(a)) for j in range(len(b)) if a[i] + b[j] <= 0.9} and len(got) == len({g[:2] for g in got})
        sums = [s for _, _, s in got]
        assert sums == sorted(sums) and all(s == a[i] + b[j] for i, j, s in got)


def planted_links():
    """Vectors near few centres in each half, with pairs just above and just below the threshold, of which many lie in different cells."""
    rng = np.random.default_rng(6)
    halves = rng.standard_normal((2, 10, 8))
    rows = []
    for i in range(500):
        v = np.concatenate([halves[h][rng.integers(10)] + 0.9 * rng.standard_normal(8) for h in (0, 1)])
        v /= np.linalg.norm(v)
        for cosine in (None, 0.9801, 0.9799, 0.99)[: rng.integers(1, 5)]:
            w = rng.standard_normal(16)
            w -= (w @ v) * v
            u = v if cosine is None else cosine * v + (1 - cosine**2) ** 0.5 * w / np.linalg.norm(w)
            rows.append((len(rows), (u * rng.uniform(0.5, 2)).tolist(), 0 if i % 3 else 1))
    return rows + [(None, rows[0][1], rows[0][2]), (len(rows), rows[0][1], rows[0][2]), (rows[7][0], rows[9][1], rows[9][2])]


@pytest.mark.parametrize("chunk", [4_096, 16])
def test_links_between_cells_of_a_grid(spark, monkeypatch, chunk):
    rows = planted_links()
    monkeypatch.setattr(embedding_dedup, "CHUNK", chunk)
    monkeypatch.setattr(embedding_dedup, "QUERY_PART", 4 * chunk)
    table = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    x = np.array([v for _, v, _ in rows])
    x /= np.linalg.norm(x, axis=1)[:, None]
    label = np.array([r[2] for r in rows])
    link = (x @ x.T >= 0.98) & (label[:, None] == label[None, :])
    np.fill_diagonal(link, False)
    books = (embedding_dedup.codebook(x[:, :8], 8), embedding_dedup.codebook(x[:, 8:], 8))
    own, visits = embedding_dedup.place(x, books, embedding_dedup.reach_of(0.98))
    assert len(set(own.tolist())) >= 32 and 1 < np.mean([len(v) for v in visits]) < 32  # of 64 cells
    assert (own[np.nonzero(link)[0]] != own[np.nonzero(link)[1]]).sum() >= 50
    got = embedding_dedup.near_duplicates(table).collect()
    vertex = [r[0] for r in rows]
    parent = {v: v for v in vertex if v is not None}

    def root(v):
        while parent[v] != v:
            v = parent[v]
        return v

    for i, j in zip(*np.nonzero(link)):
        if vertex[i] is not None and vertex[j] is not None:
            a, b = root(vertex[i]), root(vertex[j])
            parent[max(a, b)] = min(a, b)
    expected = sorted(((v, int(n), None if v is None else root(v)) for v, n in zip(vertex, link.sum(1))), key=str)
    assert sorted(((r["vec_id"], r["n_links"], r["component_id"]) for r in got), key=str) == expected
    assert all(r["kept"] == (r["vec_id"] == r["component_id"]) for r in got)


def recall_of(got, ids, x, k=10):
    hit = 0
    queries = np.flatnonzero(ids % 100 == 0)
    for q in queries:
        d = np.sqrt(((x - x[q]) ** 2).sum(1))
        d[q] = np.inf
        best = set(ids[np.lexsort((ids, d))[:k]])
        own = got[got.query_id == ids[q]].sort_values("rank")
        assert own["rank"].tolist() == list(range(1, k + 1)) and (np.diff(own.score) >= 0).all()
        assert np.abs(own.score.to_numpy() - np.sqrt(((x[np.searchsorted(ids, own.vec_id)] - x[q]) ** 2).sum(1))).max() == 0
        hit += len(best & set(own.vec_id))
    return hit / k / len(queries)


def test_forest_recall_and_order(spark, cloud):
    sf = "/root/testdata/sf0.1"
    emb = spark.read.parquet(f"{sf}/embeddings.parquet")
    table = emb.select("vec_id", "embedding").toPandas().sort_values("vec_id")
    ids, x = table.vec_id.to_numpy(), np.array(table.embedding.tolist(), dtype=np.float64)
    assert recall_of(hash_forest.nearest(emb, F.col("vec_id") % 100 == 0, block=700).toPandas(), ids, x) >= 0.9
    few = hash_forest.nearest(vectors(spark, [(0, [1.0, 0.0], 1), (100, [1.0, 0.1], 1), (3, [1.0, 0.1], 1), (4, None, 1), (5, [1.0], 2)]), F.col("vec_id") % 100 == 0).collect()
    assert [(r["query_id"], r["rank"], r["vec_id"]) for r in sorted(few)] == [(0, 1, 3), (0, 2, 100), (100, 1, 3), (100, 2, 0)]
    assert hash_forest.nearest(vectors(spark, cloud).limit(0), F.col("vec_id") % 100 == 0).count() == 0


def clustered(n=3_000, clusters=100):
    rng = np.random.default_rng(4)
    return (rng.standard_normal((clusters, 64))[rng.integers(0, clusters, n)] + 0.3 * rng.standard_normal((n, 64))).astype(np.float32).astype(np.float64)


def test_forest_of_clusters_meets_few_rows(spark):
    x, ids = clustered(), np.arange(3_000)
    got = hash_forest.nearest(vectors(spark, [(int(i), v.tolist(), 1) for i, v in zip(ids, x)]), F.col("vec_id") % 100 == 0).toPandas()
    assert recall_of(got, ids, x) >= 0.9
    forest = hash_forest.Forest(ids, x, 10)
    assert forest.met(x[::50]) < 0.1


def test_forest_descends_to_the_longest_prefix_and_ascends_in_step():
    x = clustered(400, 20)
    forest = hash_forest.Forest(np.arange(400), x, 5, trees=6, bits=12)
    asked = forest.strings(x[:40] + 0.2)
    own = forest.strings(forest.x)
    shared = 12 - hash_forest.bit_length(own[:, None, :] ^ asked[None, :, :])  # entries, queries, trees
    assert (forest.descend(asked) == shared.max(axis=0)).all()
    lengths = set()
    for q, level, met in forest.ascend(asked, 15):
        at = lambda n: np.flatnonzero((shared[:, q, :] >= n).any(axis=1))  # noqa: E731, B023
        assert met.tolist() == at(level).tolist() and len(met) >= 15 and len(at(level + 1)) < 15
        lengths.add(level)
    assert len(lengths) > 1  # of variable length


def test_forest_with_repeated_rows_and_ids(spark):
    rng = np.random.default_rng(2)
    base = rng.standard_normal((30, 8)).astype(np.float32).tolist()
    rows = [(i, base[0], 1) for i in range(300)] + [(300, base[1], 1)] * 20 + [(400 + i, v, 1) for i, v in enumerate(base)] + [(None, base[2], 1), (None, base[2], 1)]
    got = hash_forest.nearest(vectors(spark, rows), F.col("vec_id") % 100 == 0, k=5).collect()
    by = {}
    for r in sorted(got):
        by.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    assert [v for v, _ in by[0]] == [1, 2, 3, 4, 5] and [v for v, _ in by[100]] == [0, 1, 2, 3, 4] and all(s == 0 for _, s in by[0])
    assert by[300][0] == (401, 0.0) and len(by[300]) == 5 and len({v for v, _ in by[300]}) == 5
    assert set(by) == {0, 100, 200, 300, 400}


def test_components(spark):
    links = [(1, 2), (2, 3), (3, 1), (9, 8), (8, 7), (7, 6), (5, 5), (None, 1), (20, 21), (21, 22), (22, 23), (23, 24), (24, 20)] + [(100, 101 + i) for i in range(50)]
    got = {r["vertex"]: r["component"] for r in components.components(spark.createDataFrame(links, "u long, v long")).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 9: 6, 8: 6, 7: 6, 6: 6} | {i: 20 for i in range(20, 25)} | {i: 100 for i in range(100, 151)}


def test_url_rules_and_parts(spark):
    urls = [
        ("https://WWW.Example.com/en/x?q#f", "www.example.com", "/en/x", "www.example.com/en/", "allow"),
        ("http://a.example.com/en/", "a.example.com", "/en/", "example.com/en/", "block"),
        ("http://example.com/fr/1", "example.com", "/fr/1", "com/", "allow"),
        ("http://b.net/es/1", "b.net", "/es/1", "net/es/", "block"),
        ("http://notcom", "notcom", "", None, "allow"),
        ("http://x.com?y", "x.com", "", None, "allow"),
        ("no scheme", "", "", None, "allow"),
        (None, "", "", None, "allow"),
    ]
    pages = spark.createDataFrame([(i, u[0], None, "h") for i, u in enumerate(urls)], "page_id long, url string, html string, host string")
    got = {r["page_id"]: tuple(r)[1:] for r in url_filter.judge(pages).collect()}
    assert got == {i: u[1:] for i, u in enumerate(urls)}
    assert url_filter.judge(pages.limit(0)).count() == 0


def test_distrust_flows_back_and_trust_flows_on(spark):
    link = lambda h: f'<a href="https://{h}/x">'
    pages = [(1, "http://good.com/a", link("FRIEND.org") + link("friend.org")), (2, "http://friend.org/a", ""), (3, "http://bad.net/es/1", ""), (4, "http://pusher.org/", link("bad.net")), (5, "http://lone.org/", None), (6, "http://bad.net/en/1", "")]
    got = {r["page_id"]: r["verdict"] for r in url_filter.judge(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert got == {1: "allow", 2: "allow", 3: "block", 4: "block", 5: "allow", 6: "block"}
    links = spark.createDataFrame([("t", "a", "b", 1), ("t", "a", "c", 3), ("t", "c", "a", 1)], "kind string, src string, dst string, n long")
    seeds = spark.createDataFrame([("t", "a", 1.0)], "kind string, host string, seed double")
    mass = {r["host"]: r["mass"] for r in url_filter.propagate(links, seeds, 0.85, 200).collect()}
    x = {"a": 0.0, "b": 0.0, "c": 0.0}
    for _ in range(300):
        x = {"a": 0.15 + 0.85 * x["c"], "b": 0.85 * x["a"] / 4, "c": 0.85 * x["a"] * 3 / 4}
    assert all(abs(mass[h] - x[h]) < 1e-6 for h in x)


def test_mass_reaches_hosts_beyond_ten_links(spark):
    hosts = [f"h{i}.org" for i in range(14)] + ["bad.net"]
    pages = [(i, f"http://{h}/es/1", f'<a href="https://{hosts[i + 1]}/x">' if i + 1 < len(hosts) else "") for i, h in enumerate(hosts)]
    got = {r["page_id"]: r["verdict"] for r in url_filter.judge(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert got == {i: "block" for i in range(15)}


def test_mass_in_a_cycle_is_spread_whole(spark):
    links = spark.createDataFrame([("t", "a", "b", 1), ("t", "b", "a", 1)], "kind string, src string, dst string, n long")
    mass = {r["host"]: r["mass"] for r in url_filter.propagate(links, spark.createDataFrame([("t", "a", 1.0)], "kind string, host string, seed double")).collect()}
    assert abs(mass["a"] - 0.15 / (1 - 0.85**2)) < 1e-8 and abs(mass["a"] + mass["b"] - 1) < 1e-8


def test_native_operators_plan_no_python(spark, small):
    for name in ("op3_link_graph_url_filter", "op10_license_scan"):
        plan = queries.QUERIES[name](spark, small)._jdf.queryExecution().executedPlan().toString()
        assert not any(x in plan for x in ("Python", "Pandas", "Arrow", "CartesianProduct"))


def test_pipeline_stages(spark, small):
    import corpus_pipeline

    docs = spark.read.parquet(f"{small}/documents.parquet").withColumn("key", F.lit(1))
    seen = [docs]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        seen.append(stage(spark, seen[-1], small).cache())
        assert seen[-1].columns == docs.columns
    good = {r["doc_id"] for r in seen[1].collect()}
    model = quality.train(docs, spark.read.parquet(f"{small}/labels.parquet"))
    assert good == {r["doc_id"] for r in quality.score_documents(docs, model).where("predicted = 1").collect()}
    assert {r["doc_id"] for r in seen[2].collect()} == {r["doc_id"] for r in near_duplicates(seen[1]).where("kept").collect()}
    left = {r["doc_id"]: r["n_words"] - r["n_removed"] for r in substring_dedup.digest(seen[2]).collect()}
    assert left == {r["doc_id"]: len(r["text"].encode().split()) for r in seen[3].collect()}
    packed = corpus_pipeline.STAGES[-1][1](spark, seen[3], small)
    assert {r["doc_id"] for r in packed.collect()} == set(left)
    tokens = lambda df: {(r["doc_id"], r["n"]) for r in df.groupBy("doc_id").agg(F.sum("length").alias("n")).collect()}
    assert tokens(corpus_pipeline.run(spark, small)) == tokens(packed)
    empty = docs.limit(0)
    for _, stage in corpus_pipeline.STAGES:
        empty_out = stage(spark, empty, small)
        assert empty_out.count() == 0
