"""The methods to compare with: private and non-private, linear and not."""

from __future__ import annotations

import math
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import cut, drop, known_width, width
from . import arrays, noise
from .kernel import Op
from .maps import times
from .neighbours import knn, lists, matrix, summed
from .noise import start_matrix
from .step import run


def raw(points: DataFrame) -> DataFrame:
    """The features themselves as an embedding."""
    return known_width(points.select("id", F.col("x").alias("v")), width(points, "x"))


def contrast(points: DataFrame, m: int, sigma: float, alpha: float, steps: int = 7, seed: int | str = 1, op: Op | None = None) -> DataFrame:
    """The supervised map without noise."""
    return run(points, m, sigma, alpha, steps, seed, op, rescale=True).v


def second_moment(points: DataFrame, centred: bool = False) -> np.ndarray:
    """X'X, or the covariance times n: one partial matrix a task, added up."""
    d = width(points, "x")

    def sums(b: pa.RecordBatch) -> np.ndarray:
        x = np.c_[matrix(b.column(0), b.num_rows), np.ones(b.num_rows)]
        return x.T @ x

    if not d:
        return np.zeros((0, 0))
    g = summed(points.select("x"), sums, d + 1, d + 1)
    return g[:d, :d] - np.outer(g[d, :d], g[d, :d]) / g[d, d] if centred else g[:d, :d]


def pca(points: DataFrame, m: int, centred: bool = False) -> DataFrame:
    """The m leading directions of X'X (or of the covariance)."""
    return times(raw(points), arrays.top_directions(second_moment(points, centred), m))


def dp_pca_scales(epsilon: float, delta: float, split: float, target: str, calibration: str) -> tuple[float, float]:
    """Noise of the matrix (one unit row moves it by 1) and of the rows (one is moved by 2 at most)."""
    share = split if target == "both" else 1.0
    rows = noise.calibrate(epsilon * (1 - split), delta * (1 - split), 2.0, calibration) if target == "both" else 0.0
    return noise.calibrate(epsilon * share, delta * share, 1.0, calibration), rows


def noisy_directions(g: np.ndarray, m: int, tau: float, rng: np.random.Generator) -> np.ndarray:
    e = np.triu(rng.normal(0, tau, g.shape))
    return arrays.top_directions(g + e + np.triu(e, 1).T, m)


def dp_pca(points: DataFrame, m: int, epsilon: float, delta: float, split: float = 0.5, target: str = "both", calibration: str = "analytic", test_seed: int | None = None, allow_test_noise: bool = False) -> DataFrame:
    """Directions from X'X with symmetric Gaussian noise, and projected rows with noise of their own.

    ``target='directions'`` leaves the rows without noise: that publishes them. ``test_seed``
    repeats the noise of the matrix, which then hides nothing; it needs ``allow_test_noise``.
    """
    if test_seed is not None and not allow_test_noise:
        raise ValueError("test noise hides nothing; pass allow_test_noise=True in tests")
    of_matrix, of_rows = dp_pca_scales(epsilon, delta, split, target, calibration)
    v = times(raw(points), noisy_directions(second_moment(points), m, of_matrix, np.random.default_rng(test_seed)))
    return known_width(cut(noise.add(v, of_rows), "dp_pca"), m) if target == "both" else v


def projection_matrix(d: int, m: int, seed: int | str) -> np.ndarray:
    """R with entries N(0, 1 / m) from the portable source."""
    return arrays.normals(seed, np.arange(d), m) / math.sqrt(m)


def random_projection(points: DataFrame, m: int, seed: int | str = 7) -> DataFrame:
    return times(raw(points), projection_matrix(width(points, "x"), m, seed))


def dp_rp(points: DataFrame, m: int, epsilon: float, delta: float, seed: int | str = 7, calibration: str = "analytic", test_noise: int | str | None = None) -> DataFrame:
    """Random projection with noise; a row moves by 2 at most, its image by 2 times R's top singular value."""
    tau = noise.calibrate(epsilon, delta, 2 * float(np.linalg.norm(projection_matrix(width(points, "x"), m, seed), 2)), calibration)
    v = random_projection(points, m, seed)
    return noise.add_test_noise(v, tau, test_noise, True) if test_noise is not None else known_width(cut(noise.add(v, tau), "dp_rp"), m)


def _embedding(spark: SparkSession, ids: np.ndarray, y: np.ndarray) -> DataFrame:
    return known_width(spark.createDataFrame(pa.table([pa.array(ids), lists(y)], names=["id", "v"]).cast(pa.schema([("id", pa.int64()), ("v", pa.list_(pa.float64()))]))), y.shape[1])


def tsne(points: DataFrame, m: int = 2, perplexity: float = 30.0, iterations: int = 250, rate: float = 200.0, seed: int | str = 1, exaggerate: float = 12.0, log: list | None = None, exact_rows: int = 4000, max_rows: int = 1_000_000) -> DataFrame:
    """t-SNE. Up to ``exact_rows`` with the affinities of all pairs, in one place.

    Beyond, affinities are those of the 3 x ``perplexity`` nearest rows, kept as a table of
    one row a point; in each round every task adds up its points' attraction to their
    neighbours, while the driver adds up the repulsion from all places on a grid
    (``arrays.repulsion``; tasks compare all pairs where places lie too far apart for it or not in
    a plane). Places (n x m numbers) go out to all and are moved on the driver, up to ``max_rows`` of them.
    """
    spark = points.sparkSession
    n = points.count()
    if n > max_rows:
        raise ValueError(f"more than {max_rows} rows")
    if n < 3:
        return raw(points).select("id", F.slice("v", 1, m).alias("v"))
    if n <= exact_rows:
        t = points.select("id", "x").orderBy("id").toArrow()
        ids = t["id"].to_numpy()
        return _embedding(spark, ids, arrays.tsne(matrix(t["x"], n), 1e-4 * arrays.normals(seed, ids, m), perplexity, iterations, rate, exaggerate, log))
    ids = points.select("id").orderBy("id").toArrow()["id"].to_numpy()
    joint = cut(_placed(_joint_affinities(points, perplexity, n), ids), "joint")
    d = arrays.Descent(1e-4 * arrays.normals(seed, ids, m), rate, exaggerate)
    with ThreadPoolExecutor(1) as beside:
        for _ in range(iterations):
            wide = arrays.too_wide(d.y)
            apart = None if wide else beside.submit(arrays.repulsion, d.y)  # while tasks add up attractions
            sent = spark.sparkContext.broadcast((d.y, d.exaggerate))

            def forces(batches: Iterator[pa.RecordBatch], sent=sent, wide=wide) -> Iterator[pa.RecordBatch]:
                y, factor = sent.value
                for b in batches:
                    size = max(1, arrays.ENTRIES // len(y)) if wide else b.num_rows
                    for s in range(0, b.num_rows, size):
                        part = b.slice(s, size)
                        own = part.column(0).to_numpy()
                        count = pa.compute.list_value_length(part.column(1)).to_numpy()
                        i, j = np.repeat(np.arange(len(own)), count), part.column(1).flatten().to_numpy()
                        gap = y[own][i] - y[j]
                        pull = factor * part.column(2).flatten().to_numpy() / (1 + (gap * gap).sum(1))
                        f = [np.bincount(i, pull * gap[:, c], len(own)) for c in range(y.shape[1])]
                        if wide:
                            q = 1 / (1 + arrays.square_gaps(y[own], y))
                            q[np.arange(len(own)), own] = 0
                            f += [*((q * q).sum(1)[:, None] * y[own] - (q * q) @ y).T, q.sum(1)]
                        yield pa.RecordBatch.from_arrays([part.column(0), lists(np.c_[*f])], ["at", "f"])

            got = joint.mapInArrow(forces, "at long, f array<double>").toArrow()
            sent.unpersist()
            f = matrix(got["f"], len(got))[np.argsort(got["at"].to_numpy())]
            far, total = (f[:, m : 2 * m], f[:, -1].sum()) if apart is None else apart.result()
            d.move(4 * (f[:, :m] - far / total))
    drop(spark, joint)
    return _embedding(spark, ids, d.y)


def _placed(joint: DataFrame, ids: np.ndarray) -> DataFrame:
    """``(at, near, p)``: ids as places among all ids."""
    sent = joint.sparkSession.sparkContext.broadcast(ids)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            count = pa.compute.list_value_length(b.column(1)).to_numpy()
            offsets = pa.array(np.r_[0, np.cumsum(count)], pa.int32())
            at, near = (pa.array(np.searchsorted(sent.value, c.to_numpy())) for c in (b.column(0), b.column(1).flatten()))
            yield pa.RecordBatch.from_arrays([at, pa.ListArray.from_arrays(offsets, near), b.column(2)], ["at", "near", "p"])

    return joint.mapInArrow(place, "at long, near array<long>, p array<double>")


def _joint_affinities(points: DataFrame, perplexity: float, n: int) -> DataFrame:
    """``(id, near, p)``: affinities of each point to its neighbours, both ways, which sum to 1."""
    v = raw(points)
    near = knn(v, v, int(3 * perplexity)).groupBy("query_id").agg(F.sort_array(F.collect_list(F.struct("dist", "match_id"))).alias("s")).select("query_id", "s.match_id", "s.dist")

    def conditional(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            count = pa.compute.list_value_length(b.column(1)).to_numpy()
            for k in np.unique(count).tolist():  # one, unless there are few points
                some = b.filter(pa.array(count == k))
                p = arrays.row_bandwidths(matrix(some.column(2), some.num_rows), perplexity)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(some.column(0).to_numpy(), k)), some.column(1).flatten(), pa.array(p.ravel() / (2 * n))], ["i", "j", "p"])

    one = near.mapInArrow(conditional, "i long, j long, p double")
    both = one.unionByName(one.select(F.col("j").alias("i"), F.col("i").alias("j"), "p")).groupBy("i", "j").agg(F.sum("p").alias("p"))
    return both.groupBy(F.col("i").alias("id")).agg(F.collect_list(F.struct("j", "p")).alias("s")).select("id", F.col("s.j").alias("near"), F.col("s.p").alias("p"))


def dp_sne(
    points: DataFrame,
    m: int,
    epsilon: float,
    delta: float,
    sites: int = 4,
    clip: float = 0.1,
    iterations: int = 30,
    rate: float = 5.0,
    perplexity: float = 20.0,
    seed: int = 1,
    anchors: str = "role = 'public'",
    ledger: list | None = None,
    noisy: bool = True,
    max_anchors: int = 2000,
) -> DataFrame:
    """Several sites embed shared anchors together: each round every site sums the clipped forces its rows put on the anchors, with Gaussian noise; rounds are accounted as zero-concentrated privacy.

    Anchors are ``max_anchors`` public rows of least hash, a setting of the method: their
    places and affinities are held on the driver. All other rows are placed as the mean of
    their nearest anchors' places, the private ones with noise for the rest of the budget.
    """
    return dp_sne_many(points, m, [(epsilon, seed)], delta, sites, clip, iterations, rate, perplexity, anchors, ledger, noisy, max_anchors)[0]


def dp_sne_many(
    points: DataFrame,
    m: int,
    arms: list[tuple[float, int]],
    delta: float,
    sites: int = 4,
    clip: float = 0.1,
    iterations: int = 30,
    rate: float = 5.0,
    perplexity: float = 20.0,
    anchors: str = "role = 'public'",
    ledger: list | None = None,
    noisy: bool = True,
    max_anchors: int = 2000,
) -> list[DataFrame]:
    """``dp_sne`` for each (epsilon, seed) of ``arms``: affinities, which know neither, are found once, and every round of all runs is one job."""
    spark = points.sparkSession
    public = points.where(anchors).select("id", "x")
    shared = public.orderBy(F.md5(F.concat_ws(":", F.lit("anchor"), F.col("id").cast("string"))), "id").limit(max_anchors).toArrow().sort_by("id")
    ids, ax = shared["id"].to_numpy(), matrix(shared["x"], len(shared))
    if not len(ids):
        return [spark.createDataFrame([], "id long, v array<double>") for _ in arms]
    costs = [arrays.sne_round_cost(epsilon, delta, iterations) for epsilon, _ in arms]
    data = spark.sparkContext.broadcast((ids, ax))
    own = points.where(f"NOT ({anchors}) OR ({anchors}) IS NULL").select("id", F.pmod(F.xxhash64("id"), F.lit(sites)).cast("int").alias("site"), "x")
    rest = public.select("id", F.lit(-1).alias("site"), "x")

    def affinities(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, ax = data.value
        for b in batches:
            b = b.filter(pa.array(~np.isin(b.column(0).to_numpy(), ids)))
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), lists(arrays.row_bandwidths(arrays.square_gaps(matrix(b.column(2), b.num_rows), ax), perplexity))], ["id", "site", "w"])

    known = cut(own.unionByName(rest).mapInArrow(affinities, "id long, site int, w array<double>"), "affinities")
    private = known.where("site >= 0")
    sizes = {r.site: r.n for r in private.groupBy("site").agg(F.count(F.lit(1)).alias("n")).collect()}

    def forces(now: list[np.ndarray]) -> list[dict[int, np.ndarray]]:
        sent = spark.sparkContext.broadcast(now)

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict[tuple[int, int], np.ndarray] = {}
            for b in batches:
                site = b.column(0).to_numpy()
                w = matrix(b.column(1), b.num_rows)
                for s in np.unique(site).tolist():
                    for r, y in enumerate(sent.value):
                        total[r, s] = total.get((r, s), 0) + arrays.site_forces(w[site == s], y, clip)
            if total:
                run, site = (pa.array(z, pa.int32()) for z in zip(*total, strict=True))
                yield pa.RecordBatch.from_arrays([run, site, lists(np.array([f.ravel() for f in total.values()]))], ["run", "site", "f"])

        out: list[dict[int, np.ndarray]] = [{} for _ in now]
        for r in private.select("site", "w").mapInArrow(add, "run int, site int, f array<double>").toLocalIterator():  # one row a task, run and site
            out[r.run][r.site] = out[r.run].get(r.site, 0) + np.array(r.f).reshape(now[r.run].shape)
        sent.unpersist()
        return out

    ys = arrays.sne_rounds_many(ax, forces, sizes, m, [each for _, each in costs], clip, iterations, rate, perplexity, [seed for _, seed in arms], np.random.default_rng() if noisy else None)
    out = []
    for (epsilon, _), (rho, _), y in zip(arms, costs, ys, strict=True):
        if ledger is not None:
            ledger.append({"rho": rho, "rounds": iterations, "epsilon_rounds": rho + 2 * math.sqrt(rho * math.log(2 / delta)), "epsilon_rows": epsilon / 2})
        spot = times(known.select("id", "site", F.col("w").alias("v")), y)
        placed = spot.where("site >= 0").select("id", "v")
        if noisy:
            placed = cut(noise.add(placed, noise.calibrate(epsilon / 2, delta / 2, arrays.diameter(y), "analytic")), "dp_sne")
        out.append(known_width(placed.unionByName(spot.where("site < 0").select("id", "v")).unionByName(_embedding(spark, ids, y)), m))
    return out


def pure_noise(points: DataFrame, m: int, seed: int | str = "noise") -> DataFrame:
    """A release that holds nothing of the data: the control that shows what labels alone can do."""
    return start_matrix(points, m, 1.0, seed)


__all__ = ["contrast", "dp_pca", "dp_rp", "dp_sne", "dp_sne_many", "pca", "pure_noise", "random_projection", "raw", "second_moment", "tsne"]
