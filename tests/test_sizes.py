"""Queries on tables larger than the given ones, and on rows that only larger tables have."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from manifold_dp.operators import arrays, baselines, experiments, features, kernel, maps, metrics, neighbours, retrieval, sensitivity, sweep


def agree(spark, name, at, *tables):
    """The query and its SQL on the Parquet tables at ``at``."""
    duck = duckdb.connect()
    for t in tables:
        duck.execute(f"CREATE VIEW {t} AS SELECT * FROM '{at}/{t}.parquet'")
    found = duck.execute(entry.oracle_sql()[name])
    names, want = [c[0] for c in found.description], found.fetchall()
    got = [tuple(r) for r in entry.queries()[name](spark, str(at)).select(*names).collect()]
    assert sorted(map(repr, got)) == sorted(map(repr, want))


def table(at, name, sql):
    duckdb.connect().execute(f"COPY ({sql}) TO '{at}/{name}.parquet'")


def test_lateral_join_takes_two_rows_a_key(spark, tmp_path):
    """Three copies of customer 1 are one partition; a missing order key comes last among equal prices."""
    table(tmp_path, "customer", "SELECT * FROM (VALUES (1), (1), (1), (2), (3), (NULL)) t(c_custkey)")
    table(tmp_path, "orders", "SELECT * FROM (VALUES (10, 1, 5.0), (11, 1, 9.0), (12, 1, 7.0), (20, 2, 3.0), (NULL, 2, 3.0), (21, 2, 3.0), (22, 2, NULL), (30, NULL, 1.0)) t(o_orderkey, o_custkey, o_totalprice)")
    agree(spark, "join_lateral", tmp_path, "customer", "orders")


@pytest.mark.parametrize("name", ["fn_udtf", "row_bounds"])
def test_bounds_are_of_the_given_classes(spark, tmp_path, name):
    """Zero and missing vectors do not count, a lone row has no bound; a class without a name is one too."""
    rows = ", ".join(f"({i}, [{x}, 1.0]::FLOAT[], {label})" for i, (x, label) in enumerate([(1, 0), (2, 0), (3, 0), (4, 1), (5, 1), (6, 2), (7, "NULL"), (8, "NULL")]))
    table(tmp_path, "embeddings", f"SELECT * FROM (VALUES {rows}, (8, [0.0, 0.0]::FLOAT[], 0), (9, NULL, 1)) t(vec_id, embedding, label)")
    agree(spark, name, tmp_path, "embeddings")
    seen = {(r.label, r.n) for r in entry.queries()[name](spark, str(tmp_path)).select("label", "n").collect()}
    assert seen == {(0, 3), (1, 2), (None, 2)} | ({(2, 1)} if name == "fn_udtf" else set())


def test_search_by_blocks_takes_tables_of_one_origin(spark, monkeypatch):
    """Queries and rows cut from one table, as parsed_answers has them, meet by shuffle too."""
    p = spark.createDataFrame([(i, [float(i % 7), float(i % 5)]) for i in range(60)], "id long, v array<double>").cache()
    some, rest = p.where("id % 3 = 0"), p.where("id % 3 > 0")
    asked = some.where("id < 30").unionByName(some.where("id >= 30")).distinct()
    order = ["query_id", "rank"]
    assert neighbours.knn(asked, rest, 4, skip_self=False, sent=0).orderBy(*order).collect() == neighbours.knn(asked, rest, 4, skip_self=False).orderBy(*order).collect()
    want = neighbours.knn(p, p, 4).orderBy(*order).collect()
    assert neighbours.knn(p, p, 4, sent=1).orderBy(*order).collect() == want  # rows are sent, queries dealt out
    monkeypatch.setattr(neighbours, "ROWS", 7)
    assert neighbours.knn(p, p, 4, sent=0).orderBy(*order).collect() == want


def test_table_function_takes_any_number_of_rows(spark, tmp_path):
    table(tmp_path, "embeddings", "SELECT i AS vec_id, [i % 151, i % 149]::FLOAT[] AS embedding, 0 AS label FROM range(20500) t(i)")
    got = entry.queries()["fn_udtf_neighbours"](spark, str(tmp_path))
    assert got.count() == 3 * 20500


@pytest.mark.parametrize(("scale", "shift"), [(1.0, 0.0), (1e-8, 0.0), (1e9, 0.0), (1.0, 30.0)])
def test_filtered_search_equals_the_plain_one(scale, shift):
    """Copies, ties by id, and lengths far from 1: no neighbour is lost in single precision."""
    rng = np.random.default_rng(5)
    y = rng.normal(size=(5000, 8)) * scale + shift
    y[300:900] = y[7]
    ids = np.arange(5000)
    found, dist = arrays.nearest(ids[:400], y[:400], ids, y, 5)
    for i in range(0, 400, 13):
        gap = np.round(((y[i] - y) ** 2).sum(1), 12)
        gap[i] = np.inf
        best = np.lexsort((ids, gap))[:5]
        assert found[i].tolist() == best.tolist()
        assert dist[i] == pytest.approx(gap[best], rel=1e-12)


@pytest.fixture(scope="module")
def rows(spark):
    """Rows with copies, a far one, and labels of which some are missing."""
    x = np.random.default_rng(2).normal(size=(41, 5))
    x[5:8], x[40] = x[4], 40.0
    return spark.createDataFrame([(3 * i, x[i].tolist(), None if i % 9 == 0 else i % 4) for i in range(41)], "id long, x array<double>, label int").cache()


def test_pair_tables_by_rows_equal_the_joins(rows, monkeypatch):
    """The tables sent to tasks give what the joins of larger ones do."""
    v = rows.select("id", F.slice("x", 1, 2).alias("v"))
    a, b = rows.where("id > 3"), rows.where("id <= 3")
    tables = {
        "pairs": (("i", "j"), lambda: kernel.pairs(rows, 2.0)),
        "laplacian": (("i", "j"), lambda: kernel.laplacian(rows, 2.0)),
        "distortion": (("i", "j"), lambda: metrics.distortion(v, rows, 2.0).where("w < 0.999 AND w > 1e-9")),
        "norms": (("i",), lambda: sensitivity.difference_norms(a, b, 2.0, 0.1)),
    }
    got = {name: table().orderBy(*keys).collect() for name, (keys, table) in tables.items()}
    monkeypatch.setattr(kernel, "BROADCAST", 0)
    for name, (keys, table) in tables.items():
        want = table().orderBy(*keys).collect()
        assert len(got[name]) == len(want)
        assert np.allclose(np.array(got[name], float), np.array(want, float), rtol=1e-7, atol=1e-9), name


def test_blocks_are_as_few_as_tasks_need(rows):
    """801 blocks of 128 rows would be 801 copies of each row in the shuffle."""
    a, b = neighbours.cells(102_564, 102_564, 6)
    assert a * b >= 12
    assert a + b <= 8
    assert neighbours.cells(10**6, 10**6, 6) == (16, 16)
    few, one = (kernel.degrees(rows, kernel.DenseOp(2.0, block=n, broadcast=0)).orderBy("id").collect() for n in (1, 100))
    assert np.allclose(np.array(few), np.array(one), rtol=1e-12)


def test_projections_keep_what_buckets_share(rows):
    """Every edge of two rows with a common bucket, none without: what the library's join gives."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    p, radius = rows.select("id", array_to_vector("x").alias("f")), float(np.sqrt(-2.0 * np.log(0.1)))
    lsh = BucketedRandomProjectionLSH(inputCol="f", outputCol="h", bucketLength=2 * radius, numHashTables=8, seed=1).fit(p)
    near = lsh.approxSimilarityJoin(p, p, radius + 1e-9, "dist").where("datasetA.id <> datasetB.id")
    want = sorted((r.i, r.j) for r in near.select(F.col("datasetA.id").alias("i"), F.col("datasetB.id").alias("j")).collect())
    op = kernel.SparseOp(2.0, theta=0.1, mode="lsh")
    assert want == sorted((r.i, r.j) for r in op.over(rows).edges.collect())


def test_bands_meet_their_neighbours(spark, tmp_path):
    table(tmp_path, "embeddings", "SELECT i AS vec_id, [(i % 97) / 9.0 - 5, (i % 89) / 9.0]::FLOAT[] AS embedding, 0 AS label FROM range(900) t(i)")
    agree(spark, "join_range_bands", tmp_path, "embeddings")


def test_spectral_map_is_the_solution(spark, rows):
    """Eigenvalues and vectors by the default rounds, with close eigenvalues; a row without edges has no say."""
    p = rows.where("id < 120").unionByName(spark.createDataFrame([(500, [900.0] * 5, 0)], rows.schema))
    v, values = maps.spectral(p, 6.0, 3)
    got = {r.id: r.v for r in v.collect()}
    x = np.array([r.x for r in p.where("id < 500").orderBy("id").collect()])
    w = np.exp(-((x[:, None] - x[None]) ** 2).sum(2) / 6.0)
    np.fill_diagonal(w, 0)
    half = 1 / np.sqrt(w.sum(1))
    want, u = np.linalg.eigh(np.eye(len(x)) - half[:, None] * w * half)
    assert values == pytest.approx(want[1:4], abs=1e-9)
    y, u = np.array([got[i] for i in sorted(got)]), half[:, None] * u[:, 1:4]
    assert y[-1].tolist() == [0.0] * 3
    assert np.abs(y[:-1]) == pytest.approx(np.abs(u), abs=1e-6)


def test_trigrams_are_counted_without_a_shuffle(spark, tmp_path):
    """Letters beyond 16 bits count as one; short and missing texts have no row."""
    table(tmp_path, "documents", "SELECT * FROM (VALUES (1, 'abcabcabd'), (2, 'ab'), (3, NULL), (4, 'a' || chr(128512) || chr(128513) || 'é' || chr(10) || 'x'), (5, 'xyz')) t(doc_id, text), (VALUES ('en')) l(lang)")
    agree(spark, "trigram_features", tmp_path, "documents")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet").withColumnRenamed("doc_id", "id")
    assert "Exchange" not in features.trigrams(docs, "text")._jdf.queryExecution().executedPlan().toString()


def test_large_products_meet_each_pair_of_blocks_once(rows, monkeypatch):
    """Points too large to send: as before, by half the weights; in single precision to 5 digits, however long V is."""
    rows = rows.where("id < 120")
    v = rows.select("id", F.transform(F.slice("x", 1, 2), lambda z: z * 1e60).alias("v"))
    want = {r.id: r for r in kernel.DenseOp(2.0, block=8, broadcast=0).over(rows).apply(v).collect()}
    monkeypatch.setattr(kernel.DenseOp, "_blocks", None)
    for single, tol in ((False, 1e-12), (True, 1e-5)):
        got = {r.id: r for r in kernel.DenseOp(2.0, broadcast=0, both_ways=1, single=single).over(rows).apply(v).collect()}
        assert got.keys() == want.keys()
        for i, r in got.items():
            assert r.v == want[i].v
            assert r.deg == pytest.approx(want[i].deg, rel=tol, abs=1e-30)
            assert r.wv == pytest.approx(want[i].wv, rel=tol, abs=tol * 1e60)


def test_exchange_is_in_single_precision_but_for_the_release(spark, monkeypatch):
    """What is published comes from double precision; steps after it and the server's own need not."""
    p = spark.createDataFrame([(i, [float(z) for z in x], i % 3, "target" if i % 20 == 0 else "server" if i % 7 < 3 else "public") for i, x in enumerate(arrays.unit(np.random.default_rng(4).normal(size=(120, 6))))], "id long, x array<double>, label int, role string").cache()
    made, halves = [], kernel.DenseOp._halves
    sides = [p.where(f"role = '{r}'") for r in ("target", "public", "server")]
    cfg = retrieval.Config(m=3, sigma=1.0, steps=2, test_noise=1)
    want = retrieval.private_retrieve(*sides, 4, cfg).answers.orderBy("query_id", "rank").collect()
    monkeypatch.setattr(kernel, "BOTH_WAYS", 1)
    monkeypatch.setattr(kernel.DenseOp.__init__, "__defaults__", tuple(1 if d == 5e8 else d for d in kernel.DenseOp.__init__.__defaults__))
    monkeypatch.setattr(kernel.DenseOp, "_halves", lambda self, *a: (made.append(self.single), halves(self, *a))[1])
    got = retrieval.private_retrieve(*sides, 4, cfg).answers.orderBy("query_id", "rank").collect()
    assert made == [False, True, True, True, True]  # the release, the client's two free steps, the server's two
    assert [(r.query_id, r.match_id) for r in got] == [(r.query_id, r.match_id) for r in want]
    assert np.allclose([r.dist for r in got], [r.dist for r in want], atol=1e-5)


def test_sets_beyond_one_task_are_swept_by_methods_that_fit(spark, sf, monkeypatch):
    """Runs on a larger set are one job, their first steps one product a graph; measures are those of the small sets' sweep."""
    p, same = experiments.points_of(spark, sf, "emb_planted"), {"set": "e", "m": 4, "sigma": 0.25, "alpha": 0.1, "delta": 1e-5, "steps": 3, "epsilon": 1e12, "policy": "public", "targets": True}
    arms = [same | {"method": "contrast", "seed": s} for s in (1, 2)] + [same | {"method": "release", "sigma": 4.0, "m": m, "seed": s} for m in (2, 4) for s in (1, 2)]
    arms += [same | {"method": "pure_noise", "seed": s} for s in range(10)]
    arms += [same | {"method": "tsne", "seed": 1, "iterations": 20}] + [same | {"method": "dp_sne", "seed": s, "iterations": 2} for s in (1, 2)]
    want = experiments.measured(spark, {"e": p}, arms)
    monkeypatch.setattr(sweep, "ROWS", 100)
    monkeypatch.setattr(arrays, "SINGLE", 100)
    monkeypatch.setattr(arrays, "ENTRIES", 100)
    monkeypatch.setattr(experiments, "PLACED", 100)
    monkeypatch.setattr(experiments, "_distributed", None)
    made, many, apply = [], [], kernel.DenseOp.apply
    monkeypatch.setattr(kernel.DenseOp, "apply", lambda self, v: (made.append(self.single), apply(self, v))[1])
    together = baselines.dp_sne_many
    monkeypatch.setattr(baselines, "dp_sne_many", lambda *a, **kw: (many.append(len(a[2])), together(*a, **kw))[1])
    got = experiments.measured(spark, {"e": p}, arms)
    assert (made, many) == ([False], [2])
    assert [(r["method"], r["seed"], r["m"]) for r in got] == [(r["method"], r["seed"], r["m"]) for r in want]
    for g, w in zip(got, want, strict=True):
        assert g.keys() == w.keys()
        if g["method"] != "dp_sne":
            assert [g[k] for k in ("recall_at_8", "precision_at_8", "target_precision_at_8")] == pytest.approx([w[k] for k in ("recall_at_8", "precision_at_8", "target_precision_at_8")], abs=0.03), g["method"]


def test_controls_search_every_row(spark):
    """Measures of the null controls count all rows, not those of some ids."""
    at = "/root/testdata/sf0.001"
    got = {(r.set, r.method): r.precision_at_8 for r in experiments.null_controls(spark, at).collect()}
    for name in ("emb_raw", "cust_profile"):
        held = sweep.Held.of(features.feature_set(spark, at, name))
        found, _ = arrays.nearest(held.ids, held.x, held.ids, held.x, 8)
        hits = held.label[np.searchsorted(held.ids, found)] == held.label[:, None]
        assert got[name, "raw"] == pytest.approx(hits[~np.isnan(held.label)].mean(), abs=1e-12)


def test_difference_norms_add_up_sums(rows, monkeypatch):
    """Rows too large to send meet block by block: no join makes pairs or cells of the matrix; extra rows and missing labels count as in the matrix."""
    a, b = rows.where("id > 3"), rows.where("id <= 3")
    monkeypatch.setattr(kernel, "BROADCAST", 0)
    got = sensitivity.difference_norms(a, b, 2.0, 0.1)
    assert "Join" not in got._jdf.queryExecution().optimizedPlan().toString()
    want = sensitivity.difference(a, b, 2.0, 0.1).groupBy("i").agg(F.sqrt(F.sum(F.col("value") * F.col("value"))).alias("norm"))
    (i, x), (j, y) = (zip(*df.orderBy("i").collect(), strict=True) for df in (got, want))
    assert i == j and x == pytest.approx(y, rel=1e-9)


@pytest.mark.parametrize("name", ["distortion", "pairs", "laplacian"])
def test_pairs_of_large_tables_are_not_joined(rows, monkeypatch, name):
    """Blocks meet by shuffle, and pairs go on as they are made: none is joined or added up by key."""
    v = rows.select("id", F.slice("x", 1, 2).alias("v"))
    table = {"distortion": lambda: metrics.distortion(v, rows, 2.0), "pairs": lambda: kernel.pairs(rows, 2.0), "laplacian": lambda: kernel.laplacian(rows, 2.0)}[name]
    keys = ["i", "j"]
    want = table().orderBy(*keys).collect()
    monkeypatch.setattr(kernel, "BROADCAST", 0)
    monkeypatch.setattr(kernel, "ROWS", 7)
    got = table()
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("FlatMapGroupsInArrow") < (plan.index("Join") if "Join" in plan else len(plan))
    got = got.orderBy(*keys).collect()
    assert [r[:2] for r in got] == [r[:2] for r in want] and len(got) == {"laplacian": 41 * 41}.get(name, 41 * 20)
    for g, w in zip(got, want, strict=True):
        assert [x for x in g[2:] if x is not None] == pytest.approx([x for x in w[2:] if x is not None], rel=1e-7, abs=1e-9)


def test_rounding_is_that_of_spark(spark):
    """Values halfway, next to it, huge, negative, missing and none at all."""
    from manifold_dp.plans import methods

    rng = np.random.default_rng(1)
    half = (rng.integers(-(10**6), 10**6, 2000) + 0.5) / 1e6
    x = [*half, *np.nextafter(half, 9), *np.nextafter(half, -9), *rng.normal(size=2000), *(rng.normal(size=50) * 1e9), 1 / 128, -1 / 128, 0.0, -0.0, 1e300, -1e-300, float("inf"), float("nan")]
    df = spark.createDataFrame([(float(z),) for z in x] + [(None,)], "x double")
    for digits in (4, 6):
        for got, want in df.select(methods.rounded("x", digits), F.round("x", digits) + F.lit(0.0)).collect():
            assert repr(got) == repr(want)


def test_edges_are_found_as_they_are_read(rows, monkeypatch):
    """Pieces of a block's edges are handed over as they are made, of either way to meet; only a product writes them."""
    made, cut = [], kernel.cut
    monkeypatch.setattr(kernel, "cut", lambda df, name="t": made.append(name) or cut(df, name))
    op = kernel.SparseOp(2.0, theta=0.1, mode="lsh")
    order = ("i", "j")
    want = op.over(rows).edges.orderBy(*order).collect()
    assert want and not made
    monkeypatch.setattr(kernel, "BROADCAST", 0)
    monkeypatch.setattr(kernel, "ROWS", 7)
    monkeypatch.setattr(kernel, "BATCH", 3)
    met = op.over(rows)
    assert met.edges.orderBy(*order).collect() == want and not made
    for _ in range(2):
        assert met.apply(None).count() == 41
    assert made == ["edges"]
