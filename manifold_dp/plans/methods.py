"""Queries of the methods, and DuckDB SQL of those that SQL can express.

Doubles are rounded to 6 decimals (``+ 0`` makes a negative zero positive) and vectors
are laid out as rows ``(id, dim, value)``, so that both engines can be compared by value.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import dot
from ..operators import align, baselines, experiments, features, kernel, ledger, metrics, noise, release, retrieval, sensitivity
from ..operators.kernel import DenseOp, FeatureMapOp, SparseOp
from ..operators.labels import LabelOp
from ..operators.maps import spectral
from ..operators.step import contrast_step, majorant, objective, run
from ..sources import cut, folder

M, SIGMA, ALPHA, SEED = 4, 1.0, 0.1, 1
EPS, DELTA = 0.5, 1e-5

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql is not None:
            ORACLES[name or f.__name__] = sql
        return f

    return add


def r6(c: Column | str) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, 6) + F.lit(0.0)


def rounded(c: str, digits: int) -> Column:
    """``r6`` for tables of pairs: ``F.round`` makes a decimal of each value, here only of those that may lie halfway."""
    scaled = F.col(c) * F.lit(10.0**digits)
    whole = F.rint(scaled)
    clear = (F.abs(scaled) < 1e12) & (F.abs(F.abs(scaled - whole) - 0.5) > 1e-3)
    return F.when(clear, whole / F.lit(10.0**digits)).otherwise(F.round(c, digits)) + F.lit(0.0)


def laid_out(df: DataFrame, col: str = "v", key: str = "id") -> DataFrame:
    return df.select(key, F.posexplode(col).alias("dim", "value")).select(key, F.col("dim").cast("long").alias("dim"), r6("value").alias("value"))


def one(spark: SparkSession, **values: float) -> DataFrame:
    return spark.createDataFrame([tuple(float(v) for v in values.values())], ", ".join(f"{k} double" for k in values)).select(*(r6(k).alias(k) for k in values))


def planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cut(features.feature_set(spark, sf_dir, "emb_planted"), "planted")


def _q(p: DataFrame) -> DataFrame:
    return noise.start_matrix(p, M, 1.0, SEED)


# --- SQL building blocks -------------------------------------------------------

_UNIT = """
e AS (SELECT vec_id AS id, label, list_transform(embedding, lambda z: CAST(z AS DOUBLE)) AS r FROM embeddings),
en AS (SELECT id, label, r, sqrt(list_inner_product(r, r)) AS nn FROM e),
ur AS (SELECT id, label, list_transform(r, lambda z: z / nn) AS x FROM en WHERE nn > 0)"""
_PLANTED = (
    _UNIT
    + """,
pu AS (SELECT id, label, list_transform(x, lambda z, i: z + CASE WHEN i - 1 = label THEN 1e0 ELSE 0e0 END) AS x FROM ur),
pn AS (SELECT id, label, x, sqrt(list_inner_product(x, x)) AS nn FROM pu),
p AS MATERIALIZED (SELECT id, label, list_transform(x, lambda z: z / nn) AS x FROM pn)"""
)


def _normal(seed: str, i: str, j: str) -> str:
    key = f"md5('{seed}' || ':' || CAST({i} AS VARCHAR) || ':' || CAST({j} AS VARCHAR))"
    u = lambda a: f"((CAST(CAST('0x' || substr({key}, {a}, 8) AS UBIGINT) AS DOUBLE) + 0.5e0) / 4294967296e0)"
    return f"(sqrt(-2e0 * ln({u(1)})) * cos({2 * math.pi!r}e0 * {u(9)}))"


_STARTQ = f"q AS MATERIALIZED (SELECT id, label, {', '.join(f'{_normal(str(SEED), "id", str(j))} AS v{j}' for j in range(M))} FROM p)"
_W = f"w AS MATERIALIZED (SELECT a.id AS i, b.id AS j, a.label AS li, b.label AS lj, exp(-(list_distance(a.x, b.x) * list_distance(a.x, b.x)) / {SIGMA!r}e0) AS w FROM p a JOIN p b ON a.id <> b.id)"


def _gaussian_label(a: str = "li", b: str = "lj") -> str:
    return f"exp(-(({a} - {b}) * ({a} - {b})) / {SIGMA!r}e0)"


def _step(prev: str, out: str, alpha: float = ALPHA, label: str | None = None) -> str:
    ly = label or _gaussian_label()
    sums = ", ".join(f"sum(w * b.v{k}) AS w{k}, sum(({ly}) * b.v{k}) AS y{k}" for k in range(M))
    new = ", ".join(f"v{k} + 0.5e0 / deg * ({alpha!r}e0 * (e * v{k} - y{k}) - (deg * v{k} - w{k})) AS v{k}" for k in range(M))
    return f"""{out}_s AS (SELECT i, sum(w) AS deg, sum({ly}) AS e, {sums} FROM w JOIN {prev} b ON b.id = w.j GROUP BY i),
{out} AS MATERIALIZED (SELECT id, label, {new} FROM {prev} JOIN {out}_s ON i = id)"""


def _weights(out: str, src: str, sigma: float) -> str:
    return f"{out} AS MATERIALIZED (SELECT a.id AS i, b.id AS j, a.label AS li, b.label AS lj, exp(-(list_distance(a.x, b.x) * list_distance(a.x, b.x)) / {sigma!r}e0) AS w FROM {src} a JOIN {src} b ON a.id <> b.id)"


def _start(out: str, src: str, m: int, seed: str, keep: str = "id, label") -> str:
    return f"{out} AS MATERIALIZED (SELECT {keep}, {', '.join(f'{_normal(seed, "id", str(j))} AS v{j}' for j in range(m))} FROM {src})"


def _any_step(prev: str, out: str, w: str, m: int, alpha: float, sigma: float, keep: str = "id, label") -> str:
    """A contrast step on the weights ``w``; null labels have no label edges."""
    ly = f"CASE WHEN li IS NULL OR lj IS NULL THEN 0e0 ELSE exp(-((li - lj) * (li - lj)) / {sigma!r}e0) END"
    sums = ", ".join(f"sum(w * b.v{k}) AS w{k}, sum(({ly}) * b.v{k}) AS y{k}" for k in range(m))
    new = ", ".join(f"v{k} + 0.5e0 / deg * ({alpha!r}e0 * (e * v{k} - y{k}) - (deg * v{k} - w{k})) AS v{k}" for k in range(m))
    return f"""{out}_s AS (SELECT i, sum(w) AS deg, sum({ly}) AS e, {sums} FROM {w} w JOIN {prev} b ON b.id = w.j GROUP BY i),
{out} AS MATERIALIZED (SELECT {keep}, {new} FROM {prev} JOIN {out}_s ON i = id)"""


def _rescaled(prev: str, out: str, m: int, keep: str = "id, label") -> str:
    squares = " + ".join(f"v{k} * v{k}" for k in range(m))
    return f"{out} AS MATERIALIZED (SELECT {keep}, {', '.join(f'v{k} / g AS v{k}' for k in range(m))} FROM {prev}, (SELECT sqrt(sum({squares}) / (count(*) * {m}e0)) AS g FROM {prev}))"


def _as_points(prev: str, out: str, m: int, label: str = "label") -> str:
    """Unit rows of an embedding, as points."""
    n = f"sqrt({' + '.join(f'v{k} * v{k}' for k in range(m))})"
    return f"{out} AS MATERIALIZED (SELECT id, {label} AS label, [{', '.join(f'v{k} / {n}' for k in range(m))}] AS x FROM {prev})"


def _rows(table: str, m: int = M, extra: str = "") -> str:
    return " UNION ALL ".join(f"SELECT id, CAST({k} AS BIGINT) AS dim, round(v{k}, 6) + 0e0 AS value FROM {table}{extra}" for k in range(m))


_LIST_ROWS = "SELECT id, CAST(generate_subscripts(x, 1) - 1 AS BIGINT) AS dim, round(unnest(x), 6) + 0e0 AS value FROM"

# --- preparation ---------------------------------------------------------------


@query(f"WITH {_UNIT} {_LIST_ROWS} ur")
def unit_rows(spark, sf_dir):
    return laid_out(features.raw(spark, sf_dir), "x")


@query("SELECT doc_id, CAST(dense_rank() OVER (ORDER BY lang) - 1 AS INTEGER) AS label FROM documents WHERE lang IS NOT NULL UNION ALL SELECT doc_id, NULL FROM documents WHERE lang IS NULL")
def label_codes(spark, sf_dir):
    return features.label_codes(features.read(spark, sf_dir, "documents").select("doc_id", "lang"), "lang").select("doc_id", "label")


@query("SELECT doc_id, CAST(dense_rank() OVER (ORDER BY doc_id) - 1 AS INTEGER) AS label FROM documents")
def label_codes_by_range(spark, sf_dir):
    """Codes of many values, ranked by ranges."""
    return features.label_codes(features.read(spark, sf_dir, "documents").select("doc_id"), "doc_id", small=10).select("doc_id", "label")


@query(f"WITH {_PLANTED} {_LIST_ROWS} p")
def planted_features(spark, sf_dir):
    return laid_out(features.feature_set(spark, sf_dir, "emb_planted"), "x")


_TRIGRAMS = """
g AS (SELECT id, substr(text, i, 3) AS g FROM (SELECT id, text, unnest(generate_series(1, length(text) - 2)) AS i FROM src WHERE length(text) >= 3)),
c AS (SELECT id, g, count(*) AS n FROM g GROUP BY ALL),
b AS (SELECT id, CAST(CAST('0x' || substr(md5(g), 1, 4) AS UBIGINT) % 64 AS BIGINT) AS dim, CAST(sum(n) AS DOUBLE) AS n FROM c GROUP BY ALL),
s AS (SELECT id, sqrt(sum(n * n)) AS nn FROM b GROUP BY id)
SELECT s.id, d.dim, round(coalesce(b.n, 0e0) / nn, 6) + 0e0 AS value
FROM s CROSS JOIN (SELECT unnest(generate_series(0, 63)) AS dim) d LEFT JOIN b ON b.id = s.id AND b.dim = d.dim"""


@query(f"WITH src AS (SELECT doc_id AS id, text FROM documents), {_TRIGRAMS}")
def trigram_features(spark, sf_dir):
    return laid_out(features.doc_lang(spark, sf_dir), "x")


@query(
    r"WITH src AS (SELECT page_id AS id, trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<script[^>]*>.*?</script>', ' ', 'g'), '(?s)<style[^>]*>.*?</style>', ' ', 'g'), '(?s)<head[^>]*>.*?</head>', ' ', 'g'), '<[^>]*>', ' ', 'g')) AS text FROM pages), "
    + _TRIGRAMS
)
def page_features(spark, sf_dir):
    return laid_out(features.page_lang(spark, sf_dir), "x")


@query(
    """WITH li AS (SELECT l_orderkey, avg(l_discount) AS discount FROM lineitem GROUP BY 1),
per AS (SELECT o_custkey, CAST(count(*) AS DOUBLE) AS f0, sum(o_totalprice) AS f1, avg(discount) AS f2, CAST(max(date_diff('day', DATE '1990-01-01', CAST(o_orderdate AS DATE))) AS DOUBLE) AS f4
  FROM orders LEFT JOIN li ON l_orderkey = o_orderkey GROUP BY 1),
c AS (SELECT c_custkey AS id, [coalesce(f0, 0e0), coalesce(f1, 0e0), coalesce(f2, 0e0), c_acctbal, coalesce(f4, 0e0)] AS f FROM customer LEFT JOIN per ON o_custkey = c_custkey),
m AS (SELECT """
    + ", ".join(f"avg(f[{i}]) AS m{i}, stddev_pop(f[{i}]) AS s{i}" for i in range(1, 6))
    + " FROM c), z AS (SELECT id, ["
    + ", ".join(f"(f[{i}] - m{i}) / coalesce(nullif(s{i}, 0e0), 1e0)" for i in range(1, 6))
    + "] AS x FROM c, m), n AS (SELECT id, x, sqrt(list_inner_product(x, x)) AS nn FROM z), u AS (SELECT id, list_transform(x, lambda a: a / nn) AS x FROM n WHERE nn > 0) "
    + _LIST_ROWS
    + " u"
)
def customer_profile(spark, sf_dir):
    return laid_out(features.customer_profile(spark, sf_dir), "x")


@query()
def ml_text_features(spark, sf_dir):
    return laid_out(features.ml_text_features(spark, sf_dir), "x")


@query(f"WITH {_PLANTED}, {_STARTQ} {_rows('q')}")
def start_matrix(spark, sf_dir):
    return laid_out(_q(features.feature_set(spark, sf_dir, "emb_planted")))


# --- graphs and products -------------------------------------------------------


@query(f"WITH {_PLANTED}, {_W} SELECT i, j, round(w, 6) + 0e0 AS w FROM w WHERE i < j")
def kernel_pairs(spark, sf_dir):
    return kernel.pairs(planted(spark, sf_dir), SIGMA).select("i", "j", rounded("w", 6).alias("w"))


@query(f"WITH {_PLANTED}, {_W} SELECT i AS id, round(sum(w), 6) + 0e0 AS deg FROM w GROUP BY i")
def degrees(spark, sf_dir):
    return kernel.degrees(planted(spark, sf_dir), DenseOp(SIGMA)).select("id", r6("deg").alias("deg"))


@query(f"WITH {_PLANTED}, {_W} SELECT i AS id, round(sum(w), 6) + 0e0 AS deg FROM w GROUP BY i")
def degrees_by_blocks(spark, sf_dir):
    """The block form that large inputs take."""
    return kernel.degrees(planted(spark, sf_dir), DenseOp(SIGMA, block=128, broadcast=0)).select("id", r6("deg").alias("deg"))


@query(f"WITH {_PLANTED}, {_W} SELECT i, j, round(-w, 6) + 0e0 AS value FROM w UNION ALL SELECT i, i, round(sum(w), 6) + 0e0 FROM w GROUP BY i")
def laplacian_rows(spark, sf_dir):
    return kernel.laplacian(planted(spark, sf_dir), SIGMA).select("i", "j", rounded("value", 6).alias("value"))


_GAPS = " + ".join(f"(a.v{k} - b.v{k}) * (a.v{k} - b.v{k})" for k in range(M))


@query(f"WITH {_PLANTED}, {_STARTQ}, {_W} SELECT round(sum(w * ({_GAPS})), 4) + 0e0 AS energy FROM w JOIN q a ON a.id = i JOIN q b ON b.id = j WHERE i < j")
def energy(spark, sf_dir):
    p = planted(spark, sf_dir)
    e = kernel.energy(_q(p), DenseOp(SIGMA).over(p))
    return spark.createDataFrame([(float(e),)], "energy double").select((F.round("energy", 4) + F.lit(0.0)).alias("energy"))


@query(f"WITH {_PLANTED}, {_STARTQ}, c AS (SELECT label AS id, {', '.join(f'sum(v{k}) AS v{k}' for k in range(M))} FROM q GROUP BY label) {_rows('c')}")
def label_classes(spark, sf_dir):
    p = planted(spark, sf_dir)
    return laid_out(LabelOp(p).classes(_q(p)).select(F.col("label").alias("id"), F.col("s").alias("v")))


_LY = f"""y AS (SELECT a.id, sum({_gaussian_label("a.label", "b.label")}) AS e, {", ".join(f"sum({_gaussian_label('a.label', 'b.label')} * b.v{k}) AS y{k}" for k in range(M))} FROM q a JOIN q b ON a.id <> b.id GROUP BY a.id),
l AS (SELECT q.id, {", ".join(f"e * v{k} - y{k} AS v{k}" for k in range(M))} FROM q JOIN y ON y.id = q.id)"""


@query(f"WITH {_PLANTED}, {_STARTQ}, {_LY} {_rows('l')}")
def label_product(spark, sf_dir):
    p = planted(spark, sf_dir)
    return laid_out(LabelOp(p, SIGMA).apply(_q(p)).select("id", F.col("lv").alias("v")))


@query(
    f"""WITH {_PLANTED}, {_STARTQ}, {_W}
SELECT round(sum(({_GAPS}) * (w - {ALPHA!r}e0 * {_gaussian_label()})), 4) + 0e0 AS objective FROM w JOIN q a ON a.id = i JOIN q b ON b.id = j WHERE i < j"""
)
def objective_value(spark, sf_dir):
    p = planted(spark, sf_dir)
    v = objective(_q(p), DenseOp(SIGMA).over(p), LabelOp(p, SIGMA), ALPHA)
    return spark.createDataFrame([(float(v),)], "objective double").select((F.round("objective", 4) + F.lit(0.0)).alias("objective"))


@query(f"WITH {_PLANTED}, {_W} SELECT i, j, round(w, 6) + 0e0 AS w FROM w WHERE w >= 0.3e0")
def sparse_graph(spark, sf_dir):
    """The graph cut at a least weight."""
    return SparseOp(SIGMA, theta=0.3).over(planted(spark, sf_dir)).edges.select("i", "j", r6("w").alias("w"))


@query(
    f"""WITH {_PLANTED}, {_W}, r AS (SELECT i, j, w, row_number() OVER (PARTITION BY i ORDER BY round(-ln(w), 12), j) AS r FROM w),
k AS (SELECT i, j, w FROM r WHERE r <= 8) SELECT i, j, round(max(w), 6) + 0e0 AS w FROM (SELECT * FROM k UNION ALL SELECT j, i, w FROM k) GROUP BY i, j"""
)
def knn_graph(spark, sf_dir):
    return SparseOp(SIGMA, knn=8).over(planted(spark, sf_dir)).edges.select("i", "j", r6("w").alias("w"))


@query()
def lsh_graph(spark, sf_dir):
    """Edges found by random projections: a part of the exact graph."""
    return SparseOp(SIGMA, theta=0.3, mode="lsh").over(planted(spark, sf_dir)).edges.select("i", "j", rounded("w", 6).alias("w"))


@query()
def feature_map_error(spark, sf_dir):
    """Relative error of the feature-map product by kernel width and number of features."""
    p = planted(spark, sf_dir)
    v = cut(_q(p), "q")
    rows = []
    for sigma in (0.5, 1.0, 4.0):
        exact = cut(DenseOp(sigma).over(p).apply(v), "exact")
        for features_ in (64, 256):
            a = FeatureMapOp(sigma, features_).over(p).apply(v).select("id", F.col("wv").alias("a"))
            j = exact.join(a, "id").agg(F.sum(F.aggregate(F.zip_with("wv", "a", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, z: s + z)).alias("e"), F.sum(dot(F.col("wv"), F.col("wv"))).alias("n")).first()
            rows.append((sigma, features_, math.sqrt(j.e / j.n)))
    return spark.createDataFrame(rows, "sigma double, features int, error double")


# --- contrast steps ------------------------------------------------------------


def _steps(n: int, alpha: float = ALPHA, label: str | None = None) -> str:
    names = ["q", *(f"t{i}" for i in range(1, n + 1))]
    return f"WITH {_PLANTED}, {_STARTQ}, {_W}, " + ", ".join(_step(a, b, alpha, label) for a, b in zip(names, names[1:], strict=False)) + " " + _rows(names[-1])


def _stepped(spark, sf_dir, steps, **kw):
    p = planted(spark, sf_dir)
    return laid_out(run(p, M, SIGMA, kw.pop("alpha", ALPHA), steps, SEED, **kw).v)


@query(_steps(1))
def contrast_step_1(spark, sf_dir):
    return _stepped(spark, sf_dir, 1)


@query(_steps(2))
def contrast_step_2(spark, sf_dir):
    return _stepped(spark, sf_dir, 2)


@query(_steps(3))
def contrast_step_3(spark, sf_dir):
    return _stepped(spark, sf_dir, 3)


@query(_steps(3, 0.0))
def contrast_step_alpha0(spark, sf_dir):
    return _stepped(spark, sf_dir, 3, alpha=0.0)


@query(_steps(2, ALPHA, "CASE WHEN li = lj THEN 1e0 ELSE 0e0 END"))
def contrast_step_same_kernel(spark, sf_dir):
    return _stepped(spark, sf_dir, 2, label_kernel="same")


@query(_steps(2, ALPHA, f"CASE WHEN li % 3 = 0 OR lj % 3 = 0 THEN 0e0 ELSE {_gaussian_label()} END"))
def contrast_step_masked(spark, sf_dir):
    """Rows whose label is hidden have no label edges."""
    p = planted(spark, sf_dir).withColumn("label", F.when(F.col("label") % 3 != 0, F.col("label")))
    return laid_out(run(p, M, SIGMA, ALPHA, 2, SEED).v)


@query(_steps(1))
def contrast_step_by_blocks(spark, sf_dir):
    return _stepped(spark, sf_dir, 1, op=DenseOp(SIGMA, block=128, broadcast=0))


def _objectives(n: int) -> str:
    names = ["q", *(f"t{i}" for i in range(1, n + 1))]
    steps = ", ".join(_step(a, b) for a, b in zip(names, names[1:], strict=False))
    each = " UNION ALL ".join(f"SELECT CAST({t} AS INTEGER) AS t, round(sum(({_GAPS}) * (w - {ALPHA!r}e0 * {_gaussian_label()})), 4) + 0e0 AS objective FROM w JOIN {v} a ON a.id = i JOIN {v} b ON b.id = j WHERE i < j" for t, v in enumerate(names))
    return f"WITH {_PLANTED}, {_STARTQ}, {_W}, {steps} {each}"


@query(_objectives(5))
def objective_by_step(spark, sf_dir):
    """The objective never rises."""
    r = run(planted(spark, sf_dir), M, SIGMA, ALPHA, 5, SEED, monitor=True)
    return spark.createDataFrame([(x["t"], float(x["objective"])) for x in r.log], "t int, objective double").select("t", (F.round("objective", 4) + F.lit(0.0)).alias("objective"))


@query(
    f"""WITH {_PLANTED}, {_STARTQ}, {_W}, {_step("q", "t1")},
f AS (SELECT q.id, s.deg, {", ".join(f"(s.deg * q.v{k} - s.w{k}) - {ALPHA!r}e0 * (s.e * q.v{k} - s.y{k}) AS f{k}, n.v{k} - q.v{k} AS d{k}" for k in range(M))} FROM q JOIN t1_s s ON s.i = q.id JOIN t1 n ON n.id = q.id),
o AS (SELECT {", ".join(f"(SELECT sum(({_GAPS}) * (w - {ALPHA!r}e0 * {_gaussian_label()})) FROM w JOIN {v} a ON a.id = i JOIN {v} b ON b.id = j WHERE i < j) AS {name}" for v, name in (("q", "before_"), ("t1", "after_")))})
SELECT round(before_, 4) + 0e0 AS before_, round(after_, 4) + 0e0 AS after_, round(before_ + (SELECT sum(2 * ({" + ".join(f"f{k} * d{k}" for k in range(M))}) + 2 * deg * ({" + ".join(f"d{k} * d{k}" for k in range(M))})) FROM f), 4) + 0e0 AS bound_ FROM o"""
)
def majorant_check(spark, sf_dir):
    """Objective before and after a step, and the quadratic bound at the new place, which lies between."""
    p = planted(spark, sf_dir)
    op, labels = DenseOp(SIGMA).over(p), LabelOp(p, SIGMA)
    r = run(p, M, SIGMA, ALPHA, 1, SEED, keep=True)
    vals = {"before_": objective(r.steps[0], op, labels, ALPHA), "after_": objective(r.steps[1], op, labels, ALPHA), "bound_": majorant(r.steps[1], r.steps[0], op, labels, ALPHA)}
    return spark.createDataFrame([tuple(vals.values())], ", ".join(f"{k} double" for k in vals)).select(*((F.round(k, 4) + F.lit(0.0)).alias(k) for k in vals))


@query(f"WITH {_PLANTED}, {_STARTQ}, {_W} SELECT i, j, round(sqrt({_GAPS}), 6) + 0e0 AS gap, round(sqrt({_GAPS}) / list_distance(x.x, y.x), 4) + 0e0 AS ratio FROM w JOIN q a ON a.id = i JOIN q b ON b.id = j JOIN p x ON x.id = i JOIN p y ON y.id = j WHERE i < j AND list_distance(x.x, y.x) > 1e-3")
def distortion(spark, sf_dir):
    """How far images of rows lie apart, against the rows themselves."""
    p = planted(spark, sf_dir)
    d = metrics.distortion(_q(p), p, SIGMA).where(F.col("w") < math.exp(-1e-6 / SIGMA))
    return d.select("i", "j", rounded("gap", 6).alias("gap"), rounded("ratio", 4).alias("ratio"))


@query()
def early_stop(spark, sf_dir):
    r = run(planted(spark, sf_dir), M, 0.1, 0.0, 10, SEED, tol=0.05, rescale=True)
    return spark.createDataFrame([(x["t"], float(x["objective"]), float(x["log_scale"])) for x in r.log], "t int, objective double, log_scale double")


@query()
def spectral_map(spark, sf_dir):
    v, values = spectral(planted(spark, sf_dir), SIGMA, 3)
    return laid_out(v).withColumn("eigenvalues", F.lit(",".join(f"{x:.6f}" for x in values)))


@query()
def diffusion_map(spark, sf_dir):
    return laid_out(spectral(planted(spark, sf_dir), SIGMA, 3, power=2.0)[0])


FEATURES = 64


def _feature_step(prev: str, out: str) -> str:
    """A step at alpha 0 with the feature-map product: sums by feature, then by row."""
    sums = ", ".join(f"sum(z * v{k}) AS s{k}" for k in range(M))
    deg = "sum(z * s) - sum(z * z)"
    new = ", ".join(f"any_value(v{k}) + 0.5e0 / ({deg}) * ((sum(z * s{k}) - sum(z * z) * any_value(v{k})) - ({deg}) * any_value(v{k})) AS v{k}" for k in range(M))
    return f"""{out}_z AS MATERIALIZED (SELECT r, sum(z) AS s, {sums} FROM z JOIN {prev} USING (id) GROUP BY r),
{out} AS MATERIALIZED (SELECT id, {new} FROM z JOIN {out}_z USING (r) JOIN {prev} USING (id) GROUP BY id)"""


@query(
    f"""WITH {_PLANTED}, {_STARTQ}, d AS (SELECT unnest(generate_series(0, 63)) AS i), f AS (SELECT unnest(generate_series(0, {FEATURES - 1})) AS r),
om AS MATERIALIZED (SELECT i, r, sqrt(2e0 / 4e0) * {_normal("1w", "i", "r")} AS o FROM d, f),
ph AS (SELECT r, {2 * math.pi!r}e0 * (CAST(CAST('0x' || substr(md5('1p:0:' || CAST(r AS VARCHAR)), 1, 8) AS UBIGINT) AS DOUBLE) + 0.5e0) / 4294967296e0 AS ph FROM f),
xx AS (SELECT id, generate_subscripts(x, 1) - 1 AS i, unnest(x) AS a FROM p),
z AS MATERIALIZED (SELECT id, r, sqrt(2e0 / {FEATURES}e0) * cos(sum(a * o) + any_value(ph)) AS z FROM xx JOIN om USING (i) JOIN ph USING (r) GROUP BY id, r),
{_feature_step("q", "t1")}, {_feature_step("t1", "t2")} {_rows("t2")}"""
)
def step_with_feature_map(spark, sf_dir):
    """Two steps without a pair of rows."""
    p = planted(spark, sf_dir)
    return laid_out(run(p, M, 4.0, 0.0, 2, SEED, op=FeatureMapOp(4.0, FEATURES)).v)


@query(
    f"""WITH {_PLANTED}, {_STARTQ}, {_weights("w0", "p", SIGMA)}, r AS (SELECT *, row_number() OVER (PARTITION BY i ORDER BY round(-ln(w), 12), j) AS r FROM w0),
k AS (SELECT i, j, w FROM r WHERE r <= 16), w AS MATERIALIZED (SELECT i, j, 0 AS li, 0 AS lj, max(w) AS w FROM (SELECT * FROM k UNION ALL SELECT j, i, w FROM k) GROUP BY i, j),
{_step("q", "t1", 0.0)}, {_step("t1", "t2", 0.0)} {_rows("t2")}"""
)
def step_with_sparse_graph(spark, sf_dir):
    p = planted(spark, sf_dir)
    return laid_out(run(p, M, SIGMA, 0.0, 2, SEED, op=SparseOp(SIGMA, knn=16)).v)


# --- privacy -------------------------------------------------------------------


def _row_bounds(n: str, a: str, b: str) -> tuple[str, str]:
    g = f"(1e0 / (1e0 + ({n} - 1) * {b}))"
    old = f"sqrt(pow({g} * (1e0 / sqrt(({n} - 1) * {b}) + {a} / ({b} * sqrt({n} - 1))), 2) + pow({a} * {g} / {b}, 2) + pow(greatest({g}, {a} / ({n} * {b})), 2))"
    new = f"sqrt(pow(greatest(1e0, {a} / {b} - 1e0), 2) + pow(1e0 / sqrt({n} * {b}) + {a} / ({b} * sqrt({n})), 2))"
    return old, new


_OLD, _NEW = _row_bounds("n", "alpha", "exp(-4e0 / sigma)")


@query(
    f"""WITH {_UNIT}, c AS (SELECT label, CAST(count(*) AS DOUBLE) AS n FROM ur GROUP BY label HAVING count(*) >= 2)
SELECT label, CAST(n AS BIGINT) AS n, alpha, sigma, round({_OLD}, 4) + 0e0 AS old_rows, round({_NEW}, 4) + 0e0 AS new_row
FROM c, (VALUES (0e0), (0.1e0), (0.5e0)) b(alpha), (VALUES (1e0), (4e0), (16e0), (64e0)) s(sigma)"""
)
def row_bounds(spark, sf_dir):
    """The bounds for each class of two rows and more, as a client with that class would have them."""

    def bounds(n, alpha, sigma):
        r = sensitivity.row_bounds(n, alpha, sigma)
        return r["old"], r["new"]

    every = lambda *values: F.explode(F.array(*map(F.lit, values)))
    sizes = features.raw(spark, sf_dir).groupBy("label").agg(F.count(F.lit(1)).alias("n")).where("n >= 2")
    rows = sizes.select("label", "n", every(0.0, 0.1, 0.5).alias("alpha")).select("*", every(1.0, 4.0, 16.0, 64.0).alias("sigma"))
    rows = rows.withColumn("b", F.udf(bounds, "old double, new double")("n", "alpha", "sigma"))
    return rows.select("label", "n", "alpha", "sigma", (F.round("b.old", 4) + F.lit(0.0)).alias("old_rows"), (F.round("b.new", 4) + F.lit(0.0)).alias("new_row"))


def _norms(q: str, m: int = M, seed: str = str(SEED), sigma: float = 4.0) -> str:
    """Rows, and norms of the start matrix over them and over one row more: that of the next free id."""
    extra = " + ".join(f"pow({_normal(seed, 'top', str(k))}, 2)" for k in range(m))
    return f"""z0 AS (SELECT CAST(count(*) AS DOUBLE) AS n0, {" + ".join(f"sum(v{k} * v{k})" for k in range(m))} AS own, max(id) + 1 AS top FROM {q}),
zz AS (SELECT n0 - d AS n, sqrt(CASE WHEN d = 0 THEN own + ({extra}) ELSE own END) AS qn, {sigma!r}e0 AS sigma, {ALPHA!r}e0 AS alpha FROM z0, (VALUES (0), (1)) t(d) WHERE n0 - d >= 2)"""


_BOUNDS = f"b AS (SELECT max(greatest({_OLD}, {_NEW}) / 2 * sqrt(n + 1) * qn) AS uniform_, max(sqrt(n * pow({_OLD}, 2) + pow({_NEW}, 2)) / 2 * qn) AS row_split FROM zz)"


def _start_norms(p: DataFrame, m: int = M, spectral_: bool = False) -> sensitivity.StartNorms:
    return sensitivity.start_norms(noise.start_matrix(p, m, 1.0, SEED), SEED, 1.0, spectral_)


@query(f"WITH {_PLANTED}, {_STARTQ}, {_norms('q')}, {_BOUNDS} SELECT round(uniform_, 4) + 0e0 AS uniform_bound, round(row_split, 4) + 0e0 AS row_split_bound FROM b")
def sensitivity_bound(spark, sf_dir):
    """The bound counts the start matrix of one row more."""
    p = planted(spark, sf_dir)
    norms = _start_norms(p)
    u, r = (sensitivity.bound(p.count(), ALPHA, 4.0, norms, form) for form in ("uniform", "row_split"))
    return spark.createDataFrame([(u, r)], "uniform_bound double, row_split_bound double").select(*((F.round(c, 4) + F.lit(0.0)).alias(c) for c in ("uniform_bound", "row_split_bound")))


@query(
    f"""WITH {_PLANTED}, {_start("q", "p", 2, str(SEED))}, g0 AS (SELECT CAST(count(*) AS DOUBLE) AS n0, max(id) + 1 AS top, sum(v0 * v0) AS a0, sum(v0 * v1) AS b0, sum(v1 * v1) AS c0 FROM q),
g AS (SELECT n0 - d AS n, 4e0 AS sigma, {ALPHA!r}e0 AS alpha, {", ".join(f"{own}0 + CASE WHEN d = 0 THEN {_normal(str(SEED), 'top', i)} * {_normal(str(SEED), 'top', j)} ELSE 0e0 END AS {own}" for own, i, j in (("a", "0", "0"), ("b", "0", "1"), ("c", "1", "1")))} FROM g0, (VALUES (0), (1)) t(d)),
sv AS (SELECT *, sqrt((a + c) / 2 + sqrt(pow((a - c) / 2, 2) + b * b)) AS top2 FROM g)
SELECT round(max(sqrt(n * pow({_OLD}, 2) + pow({_NEW}, 2)) / 2 * top2), 4) + 0e0 AS spectral_bound FROM sv"""
)
def spectral_bound(spark, sf_dir):
    """The bound by the start matrix's greatest singular value, in the plane."""
    p = planted(spark, sf_dir)
    b = sensitivity.bound(p.count(), ALPHA, 4.0, _start_norms(p, 2, True), "spectral")
    return spark.createDataFrame([(b,)], "spectral_bound double").select((F.round("spectral_bound", 4) + F.lit(0.0)).alias("spectral_bound"))


_TAU = f"sqrt(2e0 * ln(1.25e0 / {DELTA!r})) / {EPS!r}e0"


@query(f"WITH {_PLANTED}, {_STARTQ}, {_norms('q')}, {_BOUNDS} SELECT round(uniform_ * {_TAU}, 2) + 0e0 AS tau FROM b")
def noise_scale(spark, sf_dir):
    p = planted(spark, sf_dir)
    tau = noise.calibrate(EPS, DELTA, sensitivity.bound(p.count(), ALPHA, 4.0, _start_norms(p)))
    return spark.createDataFrame([(tau,)], "tau double").select((F.round("tau", 2) + F.lit(0.0)).alias("tau"))


def _released(m: int = M, src: str = "p", q: str = "q", out: str = "r0", keep: str = "id, label") -> str:
    """The first step of ``src`` with test noise, at sigma 4."""
    noisy = ", ".join(f"v{k} + uniform_ * {_TAU} * {_normal('noise', 'id', str(k))} AS v{k}" for k in range(m))
    return f"""{_start(q, src, m, str(SEED), keep)}, {_weights(f"{out}_w", src, 4.0)}, {_any_step(q, f"{out}_t", f"{out}_w", m, ALPHA, 4.0, keep)},
{_norms(q, m)}, {_BOUNDS}, {out} AS MATERIALIZED (SELECT {keep}, {noisy} FROM {out}_t, b)"""


@query(f"WITH {_PLANTED}, {_released()} " + " UNION ALL ".join(f"SELECT id, CAST({k} AS BIGINT) AS dim, round(v{k}, 2) + 0e0 AS value FROM r0" for k in range(M)))
def noisy_first_step_testnoise(spark, sf_dir):
    """The released step, with the reproducible noise that only tests may use."""
    v, _ = release.noisy_first_step(planted(spark, sf_dir), M, 4.0, ALPHA, EPS, DELTA, seed=SEED, test_noise="noise")
    return v.select("id", F.posexplode("v").alias("dim", "value")).select("id", F.col("dim").cast("long").alias("dim"), (F.round("value", 2) + F.lit(0.0)).alias("value"))


@query(f"WITH {_PLANTED}, {_released()} SELECT round((SELECT sqrt(sum({' + '.join(f'v{k} * v{k}' for k in range(M))})) FROM r0_t) / (uniform_ * {_TAU} * sqrt((SELECT count(*) FROM p) * {M}e0)), 8) + 0e0 AS signal_to_noise FROM b")
def signal_to_noise(spark, sf_dir):
    """Norm of the step over the expected norm of its noise."""
    p = planted(spark, sf_dir)
    step = run(p, M, 4.0, ALPHA, 1, SEED).v
    _, r = release.noisy_first_step(p, M, 4.0, ALPHA, EPS, DELTA, seed=SEED, test_noise="noise")
    value = sensitivity.q_norm(step) / (r.tau * math.sqrt(r.n * M))
    return spark.createDataFrame([(value,)], "signal_to_noise double").select((F.round("signal_to_noise", 8) + F.lit(0.0)).alias("signal_to_noise"))


@query()
def noisy_first_step(spark, sf_dir):
    """A real release: its noise is drawn once and differs from run to run."""
    v, r = release.noisy_first_step(planted(spark, sf_dir), M, 4.0, ALPHA, EPS, DELTA, form="row_split", calibration="analytic")
    return laid_out(v).withColumn("tau", F.lit(r.tau))


@query()
def release_then_iterate(spark, sf_dir):
    v, _ = release.release_then_iterate(planted(spark, sf_dir), M, 4.0, ALPHA, 0.9, DELTA, 3, label_policy="masked")
    return laid_out(v)


_ROLE = "CASE WHEN CAST(CAST('0x' || substr(md5('42:' || CAST(id AS VARCHAR)), 1, 8) AS UBIGINT) AS BIGINT) % 100 < 40 THEN 'public' WHEN CAST(CAST('0x' || substr(md5('42:' || CAST(id AS VARCHAR)), 1, 8) AS UBIGINT) AS BIGINT) % 100 < 95 THEN 'server' ELSE 'target' END"
_MASKED = f"CASE WHEN {_ROLE} <> 'target' THEN label END"


def _free_steps(n: int, m: int = M, prev: str = "r0", label: str = _MASKED, keep: str = "id, label", tag: str = "f") -> str:
    """Steps on the unit rows of a release, rescaled after each."""
    out = [_as_points(prev, f"{tag}_x", m, label), _weights(f"{tag}_w", f"{tag}_x", 4.0)]
    for t in range(1, n + 1):
        out += [_any_step(prev, f"{tag}{t}r", f"{tag}_w", m, ALPHA, 4.0, keep), _rescaled(f"{tag}{t}r", f"{tag}{t}", m, keep)]
        prev = f"{tag}{t}"
    return ", ".join(out)


@query(f"WITH {_PLANTED}, {_released()}, {_free_steps(2)} " + " UNION ALL ".join(f"SELECT id, CAST({k} AS BIGINT) AS dim, round(v{k}, 5) + 0e0 AS value FROM f2" for k in range(M)))
def release_then_iterate_testnoise(spark, sf_dir):
    """Release with test noise, graph rebuilt from it, two free steps with the targets' labels hidden."""
    v, _ = release.release_then_iterate(planted(spark, sf_dir), M, 4.0, ALPHA, EPS, DELTA, 2, label_policy="masked", seed=SEED, test_noise="noise")
    return v.select("id", F.posexplode("v").alias("dim", "value")).select("id", F.col("dim").cast("long").alias("dim"), (F.round("value", 5) + F.lit(0.0)).alias("value"))


@query("SELECT * FROM (VALUES ('client', 1.1e0, CAST(2 AS BIGINT))) t(subject, epsilon, charges)")
def release_charges_ledger(spark, sf_dir):
    """Two releases of one client are charged before they are published; a third would exceed the budget and is not made."""
    p = planted(spark, sf_dir)
    book = ledger.Book(spark, f"{folder(spark)}/book-{id(p)}", 1.2)
    for eps in (0.5, 0.6, 0.7):
        try:
            release.noisy_first_step(p, M, 4.0, ALPHA, eps, DELTA, book=book)
        except ledger.BudgetExceeded:
            continue
    return ledger.spent(book.rows()).select("subject", F.col("epsilon").cast("double").alias("epsilon"), "charges")


@query()
def membership_attack(spark, sf_dir):
    """The best threshold's advantage at telling a release with a row from one without, and the most that (epsilon, delta) allows."""
    return experiments.membership_attack(spark, sf_dir)


def _gap_sql() -> str:
    def side(tag: str, where: str) -> str:
        s = f"{tag}_q AS (SELECT * FROM q WHERE {where}), {tag}_w AS MATERIALIZED (SELECT * FROM w WHERE {where.replace('id', 'i')} AND {where.replace('id', 'j')})"
        return s + ", " + _step(f"{tag}_q", f"{tag}_t").replace("FROM w JOIN", f"FROM {tag}_w AS w JOIN")

    gap = " + ".join(f"pow(coalesce(a.v{k}, q.v{k}) - coalesce(b.v{k}, q.v{k}), 2)" for k in range(M))
    return f"WITH {_PLANTED}, {_STARTQ}, {_W}, {side('a', 'id <> 0')}, {side('b', 'id >= 0')} SELECT round(sqrt(sum({gap})), 5) + 0e0 AS gap FROM q LEFT JOIN a_t a ON a.id = q.id LEFT JOIN b_t b ON b.id = q.id"


@query(_gap_sql())
def neighbour_gap(spark, sf_dir):
    """How far one row moves the first step."""
    p = planted(spark, sf_dir)
    g = sensitivity.observed(p.where("id <> 0"), p.where("id = 0"), _q(p), SIGMA, ALPHA)
    return spark.createDataFrame([(g,)], "gap double").select((F.round("gap", 5) + F.lit(0.0)).alias("gap"))


def _difference_sql() -> str:
    def side(tag: str, where: str) -> str:
        keep = f"{where.replace('id', 'i')} AND {where.replace('id', 'j')}"
        return f"""{tag}_w AS MATERIALIZED (SELECT i, j, w, {_gaussian_label()} AS y FROM w WHERE {keep}),
{tag}_d AS (SELECT i, sum(w) AS deg, sum(y) AS e FROM {tag}_w GROUP BY i),
{tag} AS (SELECT {tag}_w.i, j, (w - {ALPHA!r}e0 * y) / deg AS c FROM {tag}_w JOIN {tag}_d USING (i) UNION ALL SELECT i, i, ({ALPHA!r}e0 * e - deg) / deg FROM {tag}_d)"""

    return f"""WITH {_PLANTED}, {_W}, {side("a", "id <> 0")}, {side("b", "id >= 0")}
SELECT i, round(sqrt(sum(pow(coalesce(a.c, 0e0) - coalesce(b.c, 0e0), 2))), 6) + 0e0 AS norm FROM a FULL JOIN b USING (i, j) GROUP BY i"""


@query(_difference_sql())
def difference_rows(spark, sf_dir):
    """Norms of the difference matrix's rows."""
    p = planted(spark, sf_dir)
    return sensitivity.difference_norms(p.where("id <> 0"), p.where("id = 0"), SIGMA, ALPHA).select("i", r6("norm").alias("norm"))


# --- retrieval -----------------------------------------------------------------

_PARTIES = f"pr AS MATERIALIZED (SELECT id, label, x, {_ROLE} AS role FROM p)"


def _hash_number(text: str) -> str:
    return f"CAST(CAST('0x' || substr(md5({text}), 1, 8) AS UBIGINT) AS BIGINT)"


def _dummies(choice: int = retrieval.CHOICE) -> str:
    """A drawn group of each class first, all of the class if it is empty; in it the least hash."""
    return f"""dg AS (SELECT label, greatest(1, count(*) // {choice}) AS groups FROM pr WHERE role = 'public' GROUP BY label),
dm AS MATERIALIZED (SELECT target_id, id, label FROM (SELECT t.id AS target_id, u.id, u.label,
  row_number() OVER (PARTITION BY t.id, u.label ORDER BY CASE WHEN {_hash_number("'1:group:' || CAST(u.id AS VARCHAR)")} % groups = {_hash_number("'1:draw:' || CAST(t.id AS VARCHAR) || ':' || CAST(u.label AS VARCHAR)")} % groups THEN 0 ELSE 1 END, md5('1:' || CAST(t.id AS VARCHAR) || ':' || CAST(u.id AS VARCHAR)), u.id) AS r
  FROM pr t JOIN pr u ON t.role = 'target' AND u.role = 'public' AND u.label <> t.label JOIN dg ON dg.label = u.label) WHERE r = 1)"""


_DUMMIES = _dummies()
_CLIENT = "cl AS MATERIALIZED (SELECT id, label, x, CASE WHEN role = 'public' AND id IN (SELECT id FROM dm) THEN 'dummy' ELSE role END AS role FROM pr WHERE role IN ('target', 'public'))"


def _parties(spark, sf_dir):
    p = planted(spark, sf_dir)
    return p, p.where("role = 'target'"), p.where("role = 'public'"), p.where("role = 'server'")


@query(f"WITH {_PLANTED}, {_PARTIES} SELECT id, role FROM pr")
def roles(spark, sf_dir):
    return features.feature_set(spark, sf_dir, "emb_planted").select("id", "role")


@query(f"WITH {_PLANTED}, {_PARTIES}, {_DUMMIES} SELECT target_id, id, label FROM dm")
def dummies(spark, sf_dir):
    _, t, u, _ = _parties(spark, sf_dir)
    return retrieval.dummies(t, u).select("target_id", "id", "label")


@query(f"WITH {_PLANTED}, {_PARTIES}, {_dummies(4)} SELECT target_id, id, label FROM dm")
def dummies_by_group(spark, sf_dir):
    """Groups of about four rows, as classes of many rows are dealt; some drawn groups are empty."""
    _, t, u, _ = _parties(spark, sf_dir)
    return retrieval.dummies(t, u, choice=4).select("target_id", "id", "label")


@query(f"WITH {_PLANTED}, {_PARTIES}, {_DUMMIES} SELECT id, role FROM pr WHERE role = 'target' UNION ALL SELECT DISTINCT id, 'dummy' FROM dm UNION ALL SELECT id, role FROM pr WHERE role = 'public' AND id NOT IN (SELECT id FROM dm)")
def client_set(spark, sf_dir):
    _, t, u, _ = _parties(spark, sf_dir)
    return retrieval.client_set(t, u, retrieval.dummies(t, u)).select("id", "role")


@query(f"WITH {_PLANTED}, {_PARTIES} SELECT id, role FROM pr WHERE role IN ('server', 'public')")
def server_set(spark, sf_dir):
    _, _, u, s = _parties(spark, sf_dir)
    return retrieval.server_set(s, u).select("id", "role")


def _knn_sql(k: int, src: str = "p") -> str:
    return f"k AS MATERIALIZED (SELECT query_id, match_id, dist, CAST(row_number() OVER (PARTITION BY query_id ORDER BY dist, match_id) AS INTEGER) AS rank FROM (SELECT a.id AS query_id, b.id AS match_id, round(list_distance(a.x, b.x) * list_distance(a.x, b.x), 12) AS dist FROM {src} a JOIN {src} b ON a.id <> b.id)), t AS (SELECT * FROM k WHERE rank <= {k})"


def _exact(p: DataFrame, k: int = 8) -> DataFrame:
    v = baselines.raw(p)
    return retrieval.knn(v, v, k)


@query(f"WITH {_PLANTED}, {_knn_sql(8)} SELECT query_id, match_id, rank, round(dist, 6) + 0e0 AS dist FROM t")
def knn_exact(spark, sf_dir):
    return _exact(planted(spark, sf_dir)).select("query_id", "match_id", "rank", r6("dist").alias("dist"))


@query(
    f"""WITH {_PLANTED}, {_knn_sql(8)}, h AS (SELECT query_id, rank, CASE WHEN a.label = b.label THEN 1e0 ELSE 0e0 END AS hit FROM t JOIN p a ON a.id = query_id JOIN p b ON b.id = match_id)
SELECT CAST(k AS INTEGER) AS k, round(avg(r), 6) + 0e0 AS recall, round(avg(pr), 6) + 0e0 AS "precision", count(*) AS queries
FROM (SELECT k, query_id, max(hit) AS r, avg(hit) AS pr FROM h, (VALUES (1), (2), (4), (8)) ks(k) WHERE rank <= k GROUP BY k, query_id) GROUP BY k"""
)
def recall_table(spark, sf_dir):
    p = planted(spark, sf_dir)
    return metrics.recall_table(_exact(p), p).select("k", r6("recall").alias("recall"), r6("precision").alias("precision"), "queries")


@query(f"WITH {_UNIT}, {_knn_sql(8, 'ur')}, h AS (SELECT query_id, max(CASE WHEN a.label = b.label THEN 1e0 ELSE 0e0 END) AS hit FROM t JOIN ur a ON a.id = query_id JOIN ur b ON b.id = match_id GROUP BY 1) SELECT round(avg(hit), 6) + 0e0 AS recall_at_8 FROM h")
def recall_at_8(spark, sf_dir):
    """On labels without signal: the chance level."""
    p = features.raw(spark, sf_dir)
    return one(spark, recall_at_8=metrics.recall_at(_exact(p), p, 8))


@query(f"WITH {_PLANTED}, {_knn_sql(8)} SELECT round(avg(CASE WHEN a.label = b.label THEN 1e0 ELSE 0e0 END), 6) + 0e0 AS precision_at_8 FROM t JOIN p a ON a.id = query_id JOIN p b ON b.id = match_id")
def precision_at_8(spark, sf_dir):
    p = planted(spark, sf_dir)
    return one(spark, precision_at_8=metrics.precision_at(_exact(p), p, 8))


@query(
    f"""WITH {_PLANTED}, {_knn_sql(8)}, {_knn_sql(8, "ur").replace("k AS MATERIALIZED", "k2 AS MATERIALIZED").replace("t AS (SELECT * FROM k ", "t2 AS (SELECT * FROM k2 ")}
SELECT t.query_id, round(count(t2.match_id) / 8e0, 6) + 0e0 AS recall FROM t LEFT JOIN t2 USING (query_id, match_id) GROUP BY 1"""
)
def neighbour_overlap(spark, sf_dir):
    """Shared neighbours of planted and raw features."""
    a, b = _exact(planted(spark, sf_dir)), _exact(features.raw(spark, sf_dir))
    return metrics.set_recall(b, a, 8).select("query_id", r6("recall").alias("recall"))


@query(f"WITH {_PLANTED}, {_knn_sql(8)} SELECT query_id, match_id, rank, round(dist, 6) + 0e0 AS dist FROM t")
def knn_by_blocks(spark, sf_dir):
    """The block form that large inputs take."""
    v = baselines.raw(planted(spark, sf_dir))
    return retrieval.knn(v, v, 8, sent=0).select("query_id", "match_id", "rank", r6("dist").alias("dist"))


@query(
    f"""WITH {_PLANTED}, {_PARTIES}, {_DUMMIES}, asked AS (SELECT id FROM pr WHERE role = 'target' UNION SELECT id FROM dm),
k AS (SELECT a.id AS query_id, b.id AS match_id, CAST(row_number() OVER (PARTITION BY a.id ORDER BY round(list_distance(a.x, b.x) * list_distance(a.x, b.x), 12), b.id) AS INTEGER) AS rank FROM pr a JOIN pr b ON a.id IN (SELECT id FROM asked) AND b.role = 'server')
SELECT query_id, match_id, rank FROM k JOIN pr ON pr.id = query_id AND role = 'target' WHERE rank <= 8"""
)
def parsed_answers(spark, sf_dir):
    """Targets and dummies are all answered; the client keeps the targets' answers."""
    _, t, u, s = _parties(spark, sf_dir)
    v = lambda df: df.select("id", F.col("x").alias("v"))
    asked = v(t).unionByName(v(retrieval.dummies(t, u)).distinct())
    return retrieval.parse(retrieval.knn(asked, v(s), 8, skip_self=False), t).select("query_id", "match_id", "rank")


def _iterate_sql(n: int) -> str:
    names = ["q", *(f"t{i}" for i in range(1, n + 1))]
    steps = ", ".join(_step(a, b) for a, b in zip(names, names[1:], strict=False))
    all_ = ", ".join(f"SELECT {t} AS t, * FROM {v}" for t, v in enumerate(names)).replace(", SELECT", " UNION ALL SELECT")
    gap = " + ".join(f"pow(a.v{k} - b.v{k}, 2)" for k in range(M))
    return f"""WITH {_PLANTED}, {_STARTQ}, {_W}, {steps}, v AS MATERIALIZED ({all_}),
k AS (SELECT a.t, a.id AS query_id, a.label = b.label AS same, row_number() OVER (PARTITION BY a.t, a.id ORDER BY round({gap}, 12), b.id) AS r FROM v a JOIN v b ON a.t = b.t AND a.id <> b.id),
h AS (SELECT t, query_id, max(CASE WHEN same THEN 1e0 ELSE 0e0 END) AS hit, avg(CASE WHEN same THEN 1e0 ELSE 0e0 END) AS share FROM k WHERE r <= 8 GROUP BY t, query_id)
SELECT CAST(t AS INTEGER) AS t, round(avg(hit), 6) + 0e0 AS recall, round(avg(share), 6) + 0e0 AS "precision" FROM h GROUP BY t"""


@query(_iterate_sql(3))
def recall_by_iteration(spark, sf_dir):
    """Recall and precision at 8 of every iterate."""
    p = planted(spark, sf_dir)
    r = run(p, M, SIGMA, ALPHA, 3, SEED, keep=True)
    rows = [(t, *metrics.recall_table(retrieval.knn(v, v, 8), p, (8,)).select("recall", "precision").first()) for t, v in enumerate(r.steps)]
    return spark.createDataFrame(rows, "t int, recall double, precision double").select("t", r6("recall").alias("recall"), r6("precision").alias("precision"))


_BUCKET_GAP = "round(list_distance(a.x, c.x) * list_distance(a.x, c.x), 12)"


@query(
    f"""WITH {_PLANTED}, {_knn_sql(8)}, c AS MATERIALIZED (SELECT id, x FROM p ORDER BY md5('1:' || CAST(id AS VARCHAR)) LIMIT 12),
g AS MATERIALIZED (SELECT a.id, a.x, c.id AS bucket, row_number() OVER (PARTITION BY a.id ORDER BY {_BUCKET_GAP}, c.id) AS r FROM p a CROSS JOIN c),
f AS (SELECT q.id AS query_id, s.id AS match_id, row_number() OVER (PARTITION BY q.id ORDER BY round(list_distance(q.x, s.x) * list_distance(q.x, s.x), 12), s.id) AS r FROM g q JOIN g s ON q.bucket = s.bucket AND q.r <= 6 AND s.r = 1 AND q.id <> s.id)
SELECT t.query_id, round(count(f.match_id) / CAST(count(*) AS DOUBLE), 6) + 0e0 AS recall FROM t LEFT JOIN f ON f.query_id = t.query_id AND f.match_id = t.match_id AND f.r <= 8 GROUP BY 1"""
)
def knn_buckets(spark, sf_dir):
    """Recall of the bucket index against the exact search."""
    p = planted(spark, sf_dir)
    v = baselines.raw(p)
    return metrics.set_recall(retrieval.knn_buckets(v, v, 8, 12, 6), retrieval.knn(v, v, 8), 8).select("query_id", r6("recall").alias("recall"))


def _two(spark, sf_dir, m: int = 2):
    """Two embeddings of the public rows in the plane, by portable draws."""
    p = planted(spark, sf_dir)
    return noise.start_matrix(p, m, 1.0, "a"), noise.start_matrix(p, m, 1.0, "b")


_AB = f"ab AS MATERIALIZED (SELECT id, {', '.join(f'{_normal(s, "id", str(k))} AS {s}{k}' for s in 'ab' for k in range(2))} FROM p)"


@query(
    f"""WITH {_PLANTED}, {_AB} SELECT count(*) AS n, """
    + ", ".join(f"round(avg({s}{k}), 6) + 0e0 AS mean_{s}{k}" for s in "ab" for k in range(2))
    + ", "
    + ", ".join(f"round(avg(a{i} * b{j}) - avg(a{i}) * avg(b{j}), 6) + 0e0 AS c{i}{j}" for i in range(2) for j in range(2))
    + " FROM ab"
)
def align_moments(spark, sf_dir):
    a, b = _two(spark, sf_dir)
    s = align.moments(a, b)
    vals = {f"mean_a{k}": s["mean_src"][k] for k in range(2)} | {f"mean_b{k}": s["mean_dst"][k] for k in range(2)} | {f"c{i}{j}": s["cross"][i, j] for i in range(2) for j in range(2)}
    return one(spark, **vals).withColumn("n", F.lit(int(s["n"])).cast("long"))


_MOTION = """s AS (SELECT avg(a0) AS ma0, avg(a1) AS ma1, avg(b0) AS mb0, avg(b1) AS mb1, avg(a0 * b0) - avg(a0) * avg(b0) AS c00, avg(a0 * b1) - avg(a0) * avg(b1) AS c01, avg(a1 * b0) - avg(a1) * avg(b0) AS c10, avg(a1 * b1) - avg(a1) * avg(b1) AS c11 FROM ab),
th AS (SELECT *, atan2(c01 - c10, c00 + c11) AS t FROM s),
mv AS (SELECT (a0 - ma0) * cos(t) - (a1 - ma1) * sin(t) + mb0 - b0 AS g0, (a0 - ma0) * sin(t) + (a1 - ma1) * cos(t) + mb1 - b1 AS g1 FROM ab, th)"""


@query(f"WITH {_PLANTED}, {_AB}, {_MOTION} SELECT round((SELECT sqrt(avg(pow(a0 - b0, 2) + pow(a1 - b1, 2))) FROM ab), 6) + 0e0 AS before_, round(sqrt(avg(g0 * g0 + g1 * g1)), 6) + 0e0 AS after_ FROM mv")
def aligned_rmsd(spark, sf_dir):
    """Distance of two plane embeddings before and after the best rotation and shift."""
    a, b = _two(spark, sf_dir)
    return one(spark, before_=align.rmsd(a, b), after_=align.rmsd(align.apply(a, align.fit(a, b)), b))


@query(
    f"""WITH {_PLANTED}, {_AB}, s AS (SELECT avg(pow(a0 - b0, 2) + pow(a1 - b1, 2)) AS apart, var_pop(a0) + var_pop(a1) AS sa, var_pop(b0) + var_pop(b1) AS sb,
  {", ".join(f"avg(a{i} * b{j}) - avg(a{i}) * avg(b{j}) AS c{i}{j}" for i in range(2) for j in range(2))} FROM ab),
r AS (SELECT *, sqrt(pow(c00 + c11, 2) + pow(c01 - c10, 2)) AS turned, sqrt(pow(c00 - c11, 2) + pow(c01 + c10, 2)) AS mirrored FROM s)
SELECT round(sqrt(apart), 6) + 0e0 AS "none", round(sqrt(sa + sb - 2 * turned), 6) + 0e0 AS rigid, round(sqrt(sb - turned * turned / sa), 6) + 0e0 AS similarity, round(sqrt(sa + sb - 2 * greatest(turned, mirrored)), 6) + 0e0 AS orthogonal FROM r"""
)
def alignment_variants(spark, sf_dir):
    """Distance after each kind of motion; the plane has closed forms for all."""
    a, b = _two(spark, sf_dir)
    vals = {"none": align.rmsd(a, b)}
    for name, kw in (("rigid", {}), ("similarity", {"scale": True}), ("orthogonal", {"reflect": True})):
        vals[name] = align.rmsd(align.apply(a, align.fit(a, b, **kw)), b)
    return one(spark, **vals)


#: The exchange in the plane, with test noise and one free step: parties, both embeddings, and the motion of client onto server.
_EXCHANGE = f"""{_PLANTED}, {_PARTIES}, {_DUMMIES}, {_CLIENT}, {_released(2, "cl", "cq", "r0", "id, label, role")},
{_free_steps(1, 2, "r0", "CASE WHEN role = 'public' THEN label END", "id, label, role", "f")},
sv AS MATERIALIZED (SELECT id, label, x, role FROM pr WHERE role IN ('server', 'public')), {_start("sq", "sv", 2, "1s", "id, label, role")}, {_weights("s_w", "sv", 4.0)},
{_any_step("sq", "s1r", "s_w", 2, ALPHA, 4.0, "id, label, role")}, {_rescaled("s1r", "s1", 2, "id, label, role")},
ab AS MATERIALIZED (SELECT c.id, c.v0 AS a0, c.v1 AS a1, s.v0 AS b0, s.v1 AS b1 FROM f1 c JOIN s1 s ON s.id = c.id AND c.role = 'public' AND s.role = 'public'),
{_MOTION}"""


def _plane_exchange(spark, sf_dir) -> retrieval.Exchange:
    _, t, u, s = _parties(spark, sf_dir)
    cfg = retrieval.Config(m=2, sigma=4.0, alpha=ALPHA, epsilon=EPS, delta=DELTA, steps=1, seed=SEED, form="uniform", calibration="classic", label_policy="masked", test_noise="noise")
    return retrieval.private_retrieve(t, u, s, 8, cfg)


@query(f"WITH {_EXCHANGE} SELECT round((SELECT sqrt(avg(pow(a0 - b0, 2) + pow(a1 - b1, 2))) FROM ab), 5) + 0e0 AS before_, round(sqrt(avg(g0 * g0 + g1 * g1)), 5) + 0e0 AS after_ FROM mv")
def exchange_alignment(spark, sf_dir):
    """Anchor distance before and after alignment in a whole exchange with test noise."""
    x = _plane_exchange(spark, sf_dir)
    return spark.createDataFrame([(x.rmsd_before, x.rmsd_after)], "before_ double, after_ double").select(*((F.round(c, 5) + F.lit(0.0)).alias(c) for c in ("before_", "after_")))


@query(
    f"""WITH {_EXCHANGE}, asked AS (SELECT c.id, (v0 - ma0) * cos(t) - (v1 - ma1) * sin(t) + mb0 AS v0, (v0 - ma0) * sin(t) + (v1 - ma1) * cos(t) + mb1 AS v1 FROM f1 c, th WHERE role = 'target'),
k AS (SELECT a.id AS query_id, b.id AS match_id, CAST(row_number() OVER (PARTITION BY a.id ORDER BY round(pow(a.v0 - b.v0, 2) + pow(a.v1 - b.v1, 2), 12), b.id) AS INTEGER) AS rank FROM asked a JOIN s1 b ON b.role = 'server')
SELECT query_id, match_id, rank FROM k WHERE rank <= 8"""
)
def private_retrieve_testnoise(spark, sf_dir):
    """The whole exchange, with test noise, in the plane: the answers that the client keeps."""
    return _plane_exchange(spark, sf_dir).answers.select("query_id", "match_id", "rank")


@query()
def private_retrieve(spark, sf_dir):
    return experiments.end_to_end(spark, sf_dir)


@query(f"WITH {_PLANTED}, {_PARTIES}, {_DUMMIES}, a AS (SELECT label FROM pr WHERE role = 'target' UNION ALL SELECT label FROM dm) SELECT label, round(count(*) / CAST(sum(count(*)) OVER () AS DOUBLE), 6) + 0e0 AS share FROM a GROUP BY label")
def class_posterior(spark, sf_dir):
    """With one dummy of each other class, the queried classes say nothing of the target's."""
    _, t, u, _ = _parties(spark, sf_dir)
    return metrics.class_posterior(t.select("label").unionByName(retrieval.dummies(t, u).select("label"))).select("label", r6("share").alias("share"))


# --- baselines and measures ----------------------------------------------------


@query(
    f"""WITH {_PLANTED}, i AS (SELECT unnest(generate_series(0, 63)) AS i), r AS MATERIALIZED (SELECT i, """
    + ", ".join(f"{_normal('7', 'i', str(k))} / 2e0 AS r{k}" for k in range(M))
    + f""" FROM i), xx AS (SELECT id, generate_subscripts(x, 1) - 1 AS i, unnest(x) AS z FROM p),
pj AS (SELECT id, {", ".join(f"sum(z * r{k}) AS v{k}" for k in range(M))} FROM xx JOIN r USING (i) GROUP BY id) {_rows("pj")}"""
)
def random_projection(spark, sf_dir):
    return laid_out(baselines.random_projection(planted(spark, sf_dir), M))


_XX = "xx AS MATERIALIZED (SELECT id, generate_subscripts(x, 1) - 1 AS i, unnest(x) AS z FROM p)"


@query(f"WITH {_PLANTED}, {_XX} SELECT a.i, b.i AS j, round(sum(a.z * b.z), 6) + 0e0 AS value FROM xx a JOIN xx b USING (id) GROUP BY ALL")
def second_moment(spark, sf_dir):
    g = baselines.second_moment(planted(spark, sf_dir))
    return spark.createDataFrame([(i, j, float(g[i, j])) for i in range(len(g)) for j in range(len(g))], "i long, j long, value double").select("i", "j", r6("value").alias("value"))


@query(f"WITH {_PLANTED}, {_XX} SELECT a.i, b.i AS j, round(sum(a.z * b.z) - sum(a.z) * sum(b.z) / count(*), 6) + 0e0 AS value FROM xx a JOIN xx b USING (id) GROUP BY ALL")
def centred_gram(spark, sf_dir):
    g = baselines.second_moment(planted(spark, sf_dir), centred=True)
    return spark.createDataFrame([(i, j, float(g[i, j])) for i in range(len(g)) for j in range(len(g))], "i long, j long, value double").select("i", "j", r6("value").alias("value"))


@query(
    f"""WITH {_PLANTED}, {_STARTQ}, g AS (SELECT {", ".join(f"avg(v{k}) AS g{k}" for k in range(M))} FROM q), c AS (SELECT label, count(*) AS n, {", ".join(f"avg(v{k}) AS c{k}" for k in range(M))} FROM q GROUP BY label)
SELECT round((SELECT sum(n * ({" + ".join(f"pow(c{k} - g{k}, 2)" for k in range(M))})) FROM c, g) / (SELECT sum({" + ".join(f"pow(v{k} - c{k}, 2)" for k in range(M))}) FROM q JOIN c USING (label)), 6) + 0e0 AS ratio"""
)
def separation_ratio(spark, sf_dir):
    p = planted(spark, sf_dir)
    return one(spark, ratio=metrics.separation(_q(p), p))


@query(f"WITH {_PLANTED}, {_knn_sql(8)} SELECT query_id, match_id, rank FROM t")
def pca_keeps_distances(spark, sf_dir):
    """With all directions PCA is a rotation: neighbours stay."""
    v = baselines.pca(planted(spark, sf_dir), 64)
    return retrieval.knn(v, v, 8).select("query_id", "match_id", "rank")


@query(
    f"""WITH {_PLANTED}, i AS (SELECT unnest(generate_series(0, 63)) AS i), r AS MATERIALIZED (SELECT i, {", ".join(f"{_normal('7', 'i', str(k))} / sqrt(2e0) AS r{k}" for k in range(2))} FROM i),
g AS (SELECT sum(r0 * r0) AS a, sum(r0 * r1) AS b, sum(r1 * r1) AS c FROM r), tau AS (SELECT 2 * sqrt((a + c) / 2 + sqrt(pow((a - c) / 2, 2) + b * b)) * {_TAU} AS tau FROM g),
xx AS (SELECT id, generate_subscripts(x, 1) - 1 AS i, unnest(x) AS z FROM p), pj AS (SELECT id, {", ".join(f"sum(z * r{k}) + any_value(tau) * {_normal('rp', 'id', str(k))} AS v{k}" for k in range(2))} FROM xx JOIN r USING (i), tau GROUP BY id) {_rows("pj", 2)}"""
)
def dp_rp_testnoise(spark, sf_dir):
    """Private random projection with the reproducible noise of tests."""
    return laid_out(baselines.dp_rp(planted(spark, sf_dir), 2, EPS, DELTA, 7, "classic", "rp"))


@query()
def pca(spark, sf_dir):
    return laid_out(baselines.pca(planted(spark, sf_dir), M))


@query()
def dp_pca(spark, sf_dir):
    return laid_out(baselines.dp_pca(planted(spark, sf_dir), M, 1.0, DELTA))


@query()
def dp_rp(spark, sf_dir):
    return laid_out(baselines.dp_rp(planted(spark, sf_dir), M, 1.0, DELTA))


@query()
def tsne(spark, sf_dir):
    return laid_out(baselines.tsne(experiments.points_of(spark, sf_dir, "emb_planted"), 2, 30, 150))


@query()
def dp_sne(spark, sf_dir):
    return laid_out(baselines.dp_sne(experiments.points_of(spark, sf_dir, "emb_planted"), 2, 1.0, DELTA, iterations=8))


_DOCS = (
    f"src AS (SELECT doc_id AS id, text FROM documents), {_TRIGRAMS[: _TRIGRAMS.index('SELECT s.id, d.dim')].rstrip()}".rstrip(",")
    + """, p AS MATERIALIZED (SELECT v.id, any_value(lang) AS label, list(v.n ORDER BY v.dim) AS x FROM (SELECT s.id, d.dim, coalesce(b.n, 0e0) / nn AS n FROM s CROSS JOIN (SELECT unnest(generate_series(0, 63)) AS dim) d LEFT JOIN b ON b.id = s.id AND b.dim = d.dim) v JOIN documents ON doc_id = v.id GROUP BY v.id)"""
)


@query(
    f"""WITH {_DOCS}, {_knn_sql(8)}, h AS (SELECT query_id, rank, CASE WHEN a.label = b.label THEN 1e0 ELSE 0e0 END AS hit FROM t JOIN p a ON a.id = query_id AND a.label IS NOT NULL JOIN p b ON b.id = match_id)
SELECT CAST(k AS INTEGER) AS k, round(avg(r), 6) + 0e0 AS recall, round(avg(pr), 6) + 0e0 AS "precision", count(*) AS queries
FROM (SELECT k, query_id, max(hit) AS r, avg(hit) AS pr FROM h, (VALUES (1), (2), (4), (8)) ks(k) WHERE rank <= k GROUP BY k, query_id) GROUP BY k"""
)
def baseline_raw(spark, sf_dir):
    """Raw features of all documents."""
    p = experiments.points_of(spark, sf_dir, "doc_lang")
    return metrics.recall_table(_exact(p), p).select("k", r6("recall").alias("recall"), r6("precision").alias("precision"), "queries")


@query()
def baseline_contrast(spark, sf_dir):
    p = experiments.points_of(spark, sf_dir, "emb_planted")
    v = baselines.contrast(p, 16, 0.1, 0.0)
    return metrics.recall_table(retrieval.knn(v, v, 8), p)


# --- workloads -----------------------------------------------------------------


@query()
def w1_class_picture(spark, sf_dir):
    return experiments.class_picture(spark, sf_dir)


@query()
def w2_convergence(spark, sf_dir):
    return experiments.convergence(spark, sf_dir)


@query()
def w3_parameters(spark, sf_dir):
    return experiments.grid(spark, sf_dir)


@query()
def w3_private_parameters(spark, sf_dir):
    return experiments.grid(spark, sf_dir, private=True)


@query()
def w3_choice(spark, sf_dir):
    """The value of each parameter that held-out rows choose."""
    return experiments.choice(spark, sf_dir)


@query()
def w4_privacy_utility(spark, sf_dir):
    return experiments.privacy_utility(spark, sf_dir)


@query()
def w5_alignment(spark, sf_dir):
    return experiments.alignment(spark, sf_dir)


@query()
def w6_end_to_end(spark, sf_dir):
    return experiments.end_to_end(spark, sf_dir, "doc_lang")


@query()
def w6_without_noise(spark, sf_dir):
    """The same exchange without noise, at a bandwidth that serves retrieval: the ceiling."""
    return experiments.end_to_end(spark, sf_dir, "doc_lang", retrieval.Config(sigma=0.1, alpha=0.0, steps=6, private=False))


@query()
def w7_cost(spark, sf_dir):
    return experiments.cost(spark, sf_dir)


@query()
def w8_null_controls(spark, sf_dir):
    return experiments.null_controls(spark, sf_dir)


@query()
def w9_label_leak(spark, sf_dir):
    return experiments.label_leak(spark, sf_dir, steps=4)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three contrast steps on planted features."""
    return QUERIES["contrast_step_3"](spark, sf_dir)


__all__ = ["ORACLES", "QUERIES", "contrast_step", "flagship"]
