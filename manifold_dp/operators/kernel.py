"""Gaussian kernel graphs: pair tables for small inputs, and products with a matrix that never store the graph.

An operator is made for points ``(id, x)``; ``apply(V)`` returns ``(id, v, deg, wv)``: for each
row of an embedding ``V (id, v)`` itself, its degree and its row of W V.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import gauss_weight
from ..sources import cut, known_width, width
from .arrays import Filter, both_products, measured, normals, product, uniforms, weights
from .neighbours import ROWS, SHARE, as_vector, block, cells, dealt, every, knn, lists, matrix, summed, vector_sum

#: Bytes that may be sent to every task; beyond it, the block form is used.
BROADCAST = 64 << 20
#: Pairs from which a product computes each weight once for both its rows.
BOTH_WAYS = 5e8
#: Share of distinct points up to which rows of equal points meet others as one.
DISTINCT = 0.8
PRODUCT = "id long, v array<double>, deg double, wv array<double>"
_NAMES = ["id", "v", "deg", "wv"]


def weight(x: Column, y: Column, sigma: float) -> Column:
    return gauss_weight(x, y, sigma)


#: Pairs that a task hands over at once, rows and columns of the tiles they come from, and rows of a block whose pairs are written out.
BATCH, PATCH, SIDE = 1 << 17, (256, 2048), 4096
Arrays = dict[str, np.ndarray]


def by_blocks(points: DataFrame, of: Callable[[Arrays, Arrays | None], Iterator[Arrays]], schema: str, *more: str, side: int = SIDE) -> DataFrame:
    """A table made from all unordered pairs of rows: each block of rows meets each other one once, in a task of its own.

    ``of(a, b)`` gets the rows of two blocks as arrays ``id``, ``x`` and the columns ``more``;
    ``b`` is none where ``a`` meets itself. It yields pieces of the table, which go on as they
    are made: no task holds its part of it. Points of ``BROADCAST`` bytes at most are sent to
    all tasks and dealt into blocks of ``side`` rows at most, more meet by shuffle.
    """
    points, spark = points.select("id", "x", *more), points.sparkSession
    vectors = [c for c, kind in points.dtypes if kind.startswith("array")]
    n, *sizes = points.agg(F.count(F.lit(1)), *(F.max(F.size(c)) for c in vectors)).first()
    sent = n * 8 * (sum(z or 0 for z in sizes) + len(points.columns) - len(vectors)) <= BROADCAST
    k = max(1, -(-n // (side if sent else ROWS)))
    while k * (k + 1) // 2 < min(8 * spark.sparkContext.defaultParallelism, -(-(n**2) // SHARE)):
        k += 1
    if sent:
        data, edges, met = spark.sparkContext.broadcast(_arrays(points.orderBy("id").toArrow())), [n * i // k for i in range(k + 1)], [(i, j) for i in range(k) for j in range(i, k)]

        def own(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for i, j in (met[at] for at in batch.column(0).to_pylist()):
                    a, b = (_rows_at(data.value, slice(edges[q], edges[q + 1])) for q in (i, j))
                    yield from _pieces(of(a, None if i == j else b))

        return spark.range(0, len(met), 1, len(met)).mapInArrow(own, schema)
    dealt_out = points.withColumns({"_b": block(F.col("id"), k), "_q": every(k)})
    dealt_out = dealt_out.select("id", "x", *more, "_b", F.least("_b", "_q").alias("_i"), F.greatest("_b", "_q").alias("_j"))

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = _arrays(pa.Table.from_batches(list(batches)))
        i, j = t["_i"][0], t["_j"][0]
        yield from _pieces(of(_rows_at(t, t["_b"] == i), None if i == j else _rows_at(t, t["_b"] == j)))

    return dealt_out.groupBy("_i", "_j").applyInArrow(meet, schema)


def _arrays(t: pa.Table) -> Arrays:
    return {c: matrix(t[c], len(t)) if pa.types.is_list(t[c].type) else t[c].to_numpy(zero_copy_only=False) for c in t.column_names}


def _rows_at(t: Arrays, at: slice | np.ndarray) -> Arrays:
    return {c: z[at] for c, z in t.items()}


def _pieces(tables: Iterator[Arrays]) -> Iterator[pa.RecordBatch]:
    for t in tables:
        piece = pa.RecordBatch.from_arrays([lists(z) if z.ndim == 2 else pa.array(z) for z in t.values()], list(t))
        for i in range(0, len(piece), BATCH):
            yield piece.slice(i, BATCH)


def patches(a: Arrays, b: Arrays | None) -> Iterator[tuple[Arrays, Arrays, Callable[[np.ndarray], np.ndarray]]]:
    """Rows and columns of the tiles of two blocks, or of one whose pairs count once, and what lays out the cells of a tile that count: those of different ids."""
    other = a if b is None else b
    for i in range(0, len(a["id"]), PATCH[0]):
        rows = _rows_at(a, slice(i, i + PATCH[0]))
        for j in range(0 if b is not None else i - i % PATCH[1], len(other["id"]), PATCH[1]):
            cols = _rows_at(other, slice(j, j + PATCH[1]))
            keep = rows["id"][:, None] != cols["id"][None]
            if b is None and j < i + PATCH[0]:
                keep &= np.arange(i, i + len(rows["id"]))[:, None] < np.arange(j, j + len(cols["id"]))[None]
            yield rows, cols, partial(_cells, keep, bool(keep.all()))


def _cells(keep: np.ndarray, whole: bool, z: np.ndarray) -> np.ndarray:
    z = np.broadcast_to(z, keep.shape)
    return z.ravel() if whole else z[keep]


def _weights(rows: Arrays, cols: Arrays, sigma: float) -> np.ndarray:
    return weights(rows["id"], rows["x"], cols["id"], cols["x"], sigma)


def pairs(points: DataFrame, sigma: float) -> DataFrame:
    """``(i, j, w)`` for all unordered pairs ``i < j``."""

    def of(a: Arrays, b: Arrays | None) -> Iterator[Arrays]:
        for rows, cols, kept in patches(a, b):
            i, j = kept(rows["id"][:, None]), kept(cols["id"][None])
            yield {"i": np.minimum(i, j), "j": np.maximum(i, j), "w": kept(_weights(rows, cols, sigma))}

    return by_blocks(points, of, "i long, j long, w double")


def degrees(points: DataFrame, op: Op) -> DataFrame:
    """``(id, deg)``: row sums of the graph, without the diagonal."""
    return op.over(points).apply(None).select("id", "deg")


def laplacian(points: DataFrame, sigma: float) -> DataFrame:
    """``(i, j, value)`` with the diagonal, which is a product of its own: no pair is added up by key."""

    def of(a: Arrays, b: Arrays | None) -> Iterator[Arrays]:
        for rows, cols, kept in patches(a, b):
            i, j, value = kept(rows["id"][:, None]), kept(cols["id"][None]), -kept(_weights(rows, cols, sigma))
            yield {"i": i, "j": j, "value": value}
            yield {"i": j, "j": i, "value": value}

    own = degrees(points, DenseOp(sigma, max_pairs=math.inf)).select(F.col("id").alias("i"), F.col("id").alias("j"), F.col("deg").alias("value"))
    return by_blocks(points, of, "i long, j long, value double").unionByName(own)


class Op:
    """Base of the operators; ``over`` binds one to its points."""

    points: DataFrame

    def over(self, points: DataFrame) -> Op:
        import copy

        new = copy.copy(self)
        new.points = points.select("id", "x")
        new.prepare()
        return new

    def prepare(self) -> None:
        pass

    def apply(self, v: DataFrame | None) -> DataFrame:
        raise NotImplementedError

    def close(self) -> None:
        """Delete what the operator wrote for itself."""

    def _rows(self, v: DataFrame | None) -> DataFrame:
        if v is None:
            return known_width(self.points.withColumn("v", F.array(F.lit(0.0))), 1)
        return known_width(self.points.join(v.select("id", "v"), "id"), width(v))


def _check_pairs(n: int, most: float) -> None:
    if float(n) ** 2 > most:
        raise ValueError(f"{n} rows make more than {most:g} pairs; use FeatureMapOp, or a sparse graph found by projections")


def within(x: np.ndarray, y: np.ndarray, radius: float) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Places and squared distances of all pairs whose distance is ``radius`` at most, tile by tile."""
    quick = Filter(x, y)
    for i in range(0, len(x), PATCH[0]):
        rows = slice(i, i + PATCH[0])
        limit = quick.limit(np.full(len(x[rows]), radius**2 * (1 + 1e-12)), rows)
        for j in range(0, len(y), PATCH[1]):
            cols = slice(j, j + PATCH[1])
            r, c = quick.under(rows, cols, limit)
            gap = measured(x[rows], y[cols], r, c)
            keep = np.sqrt(gap) <= radius
            yield r[keep] + i, c[keep] + j, gap[keep]


def _share(x: np.ndarray, r: np.ndarray, y: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Whether rows ``r`` of ``x`` and ``c`` of ``y`` are equal in some column; later columns are asked only for those that were not yet."""
    out, left = np.zeros(len(r), bool), np.arange(len(r))
    for k in range(x.shape[1]):
        same = x[:, k][r[left]] == y[:, k][c[left]]
        out[left[same]] = True
        left = left[~same]
    return out


class DenseOp(Op):
    """Exact: every pair, as blocks of rows against blocks of rows in matrix arithmetic.

    If points and V fit in ``broadcast`` bytes they are sent to all tasks (points once, V in
    each product) and nothing is shuffled, or from ``both_ways`` pairs on, each unordered pair
    of blocks is a task and each weight is computed once for both its rows; else rows are dealt into blocks of ``block`` rows and
    more, as few as tasks can hold and are busy with, each block meets each other one, and
    the partial sums of a row are added by its id. From ``both_ways`` pairs on, rows of equal
    points, if there are many, meet others as one point with the sum of their V: their weights are equal.
    ``single``: weights of such products may be in single precision; not for a released step.
    """

    def __init__(self, sigma: float, block: int = 4096, broadcast: int = BROADCAST, max_pairs: float = 1e12, both_ways: float = BOTH_WAYS, single: bool = False):
        self.sigma, self.block, self.broadcast, self.max_pairs, self.both_ways, self.single = sigma, block, broadcast, max_pairs, both_ways, single

    def prepare(self) -> None:
        self.n, d, points = self.points.agg(F.count(F.lit(1)), F.max(F.size("x")), F.approx_count_distinct("x")).first()
        self.d, self.known, self.met = d or 0, None, None
        if self.n**2 >= self.both_ways and points <= DISTINCT * self.n:  # an estimate will do: it chooses the way, not the result
            self.of = self.points.groupBy("x").agg(F.min("id").alias("of"))
            self.met = DenseOp(self.sigma, self.block, self.broadcast, self.max_pairs, self.both_ways, self.single)
            self.met.points = self.of.select(F.col("of").alias("id"), "x")
            self.met.n, self.met.d, self.met.known, self.met.met = self.of.count(), self.d, None, None
        _check_pairs(self.met.n if self.met else self.n, self.max_pairs)

    def apply(self, v: DataFrame | None) -> DataFrame:
        m = 1 if v is None else width(v)
        if self.met is not None:
            return known_width(self._equal(self._rows(v), m), m)
        if self.n * (self.d + m + 1) * 8 <= self.broadcast:
            return known_width(self._sent(v), m)
        return known_width(self._block_pairs(v, m) if self.n**2 >= self.both_ways else self._blocks(v, m), m)

    def _equal(self, rows: DataFrame, m: int) -> DataFrame:
        """The product of the distinct points with sums over their rows; equal points but itself add to a row with weight 1."""
        rows = rows.join(self.of, "x").select("id", "v", "of")
        sums = rows.groupBy(F.col("of").alias("id")).agg(*vector_sum("v", m), F.count(F.lit(1)).cast("double").alias(f"_s{m}")).select("id", as_vector(m + 1, "v"))
        met = self.met.apply(known_width(sums, m + 1)).select(F.col("id").alias("of"), F.zip_with("v", "wv", lambda a, b: a + b).alias("_all"))
        wv = F.zip_with(F.slice("_all", 1, m), "v", lambda a, b: a - b)
        return rows.join(met, "of").select("id", "v", (F.element_at("_all", m + 1) - 1).alias("deg"), wv.alias("wv"))

    def _sent(self, v: DataFrame | None) -> DataFrame:
        sc = self.points.sparkSession.sparkContext
        if self.known is None:
            t = self.points.orderBy("id").toArrow()
            ids = t["id"].to_numpy()
            self.known = ids, sc.broadcast((ids, matrix(t["x"], len(ids))))
        ids, data = self.known
        if v is None:
            at, values = ids, np.zeros((len(ids), 1))
        else:
            t = v.select("id", "v").orderBy("id").toArrow()
            at, values = t["id"].to_numpy(), matrix(t["v"], len(t))
        sent, sigma = sc.broadcast((at, values)), self.sigma
        if self.n**2 >= self.both_ways and np.array_equal(ids, at):
            return self._halves(data, sent)

        def multiply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            (ids, x), (at, v) = data.value, sent.value
            if len(ids) != len(at):  # rows without v take no part
                both = np.isin(ids, at)
                ids, x = ids[both], x[both]
            for b in batches:
                own = b.column(0).to_numpy()
                here = np.isin(own, ids)
                if here.any():
                    own = own[here]
                    deg, wv = product(own, matrix(b.column(1), b.num_rows)[here], ids, x, v, sigma)
                    yield pa.RecordBatch.from_arrays([pa.array(own), lists(v[np.searchsorted(at, own)]), pa.array(deg), lists(wv)], _NAMES)

        return dealt(self.points, self.n**2).mapInArrow(multiply, PRODUCT)

    def _halves(self, data, sent) -> DataFrame:
        """The product by unordered pairs of blocks; partial sums, two blocks a task, are added by block."""
        spark, sigma, n, single = self.points.sparkSession, self.sigma, self.n, self.single
        k = math.ceil(math.sqrt(8 * spark.sparkContext.defaultParallelism))
        met = [(i, j) for i in range(k) for j in range(i, k)]
        edges = [n * i // k for i in range(k + 1)]

        def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            (ids, x), (_, v) = data.value, sent.value
            for b in batches:
                for at in b.column(0).to_pylist():
                    i, j = (slice(edges[q], edges[q + 1]) for q in met[at])
                    vi, vj = (np.c_[v[s], np.ones(len(ids[s]))] for s in (i, j))
                    here, there = both_products(ids[i], x[i], ids[j], x[j], None if i == j else vi, vj, sigma, single)
                    for q, sums in zip(met[at], (here, there), strict=True):
                        if sums is not None:
                            yield pa.RecordBatch.from_arrays([pa.array([q], pa.int32()), lists(sums.reshape(1, -1))], ["q", "s"])

        def add(t: pa.Table) -> pa.Table:
            (ids, _), (_, v) = data.value, sent.value
            q = t["q"][0].as_py()
            own = slice(edges[q], edges[q + 1])
            total = sum(c.values.to_numpy()[a:e] for c in t["s"].chunks for a, e in zip(c.offsets[:-1].to_pylist(), c.offsets[1:].to_pylist(), strict=True)).reshape(-1, v.shape[1] + 1)
            return pa.table([pa.array(ids[own]), lists(v[own]), pa.array(total[:, -1].copy()), lists(total[:, :-1])], names=_NAMES)

        return spark.range(0, len(met), 1, len(met)).mapInArrow(part, "q int, s array<double>").groupBy("q").applyInArrow(add, PRODUCT)

    def _block_pairs(self, v: DataFrame | None, m: int) -> DataFrame:
        """The product by unordered pairs of blocks that meet by shuffle; partial sums are added by id."""
        both, sigma, single = self._rows(v), self.sigma, self.single
        k = max(-(-self.n // ROWS), math.ceil(math.sqrt(8 * both.sparkSession.sparkContext.defaultParallelism)))
        own = both.select("id", "x", "v", block(F.col("id"), k).alias("b"), every(k).alias("q"))
        met = own.select("id", "x", "v", "b", F.least("b", "q").alias("i"), F.greatest("b", "q").alias("j"))

        def part(t: pa.Table) -> pa.Table:
            ids, x, v, b = t["id"].to_numpy(), matrix(t["x"], len(t)), matrix(t["v"], len(t)), t["b"].to_numpy()
            v, i, j = np.c_[v, np.ones(len(v))], b == t["i"][0].as_py(), b == t["j"][0].as_py()
            here, there = both_products(ids[i], x[i], ids[j], x[j], None if (i == j).all() else v[i], v[j], sigma, single)
            at, sums = (ids[i], here) if there is None else (np.r_[ids[i], ids[j]], np.r_[here, there])
            return pa.table([pa.array(at), lists(sums)], names=["id", "s"])

        parts = met.groupBy("i", "j").applyInArrow(part, "id long, s array<double>")
        added = parts.groupBy("id").agg(*vector_sum("s", m + 1)).select("id", as_vector(m + 1, "s"))
        return both.select("id", "v").join(added, "id").select("id", "v", F.element_at("s", m + 1).alias("deg"), F.slice("s", 1, m).alias("wv"))

    def _blocks(self, v: DataFrame | None, m: int) -> DataFrame:
        most = max(1, -(-self.n // self.block))
        both = self._rows(v)
        na, nb = (min(most, k) for k in cells(self.n, self.n, both.sparkSession.sparkContext.defaultParallelism))
        left = both.select(F.col("id").alias("i"), F.col("x").alias("xi"), block(F.col("id"), na).alias("bi"), every(nb).alias("bj"))
        right = both.select(F.col("id").alias("j"), F.col("x").alias("xj"), "v", block(F.col("id"), nb).alias("bj"), every(na).alias("bi"))
        sigma = self.sigma

        def part(a: pa.Table, b: pa.Table) -> pa.Table:
            names = ["id", "deg", "wv"]
            if not len(a) or not len(b):
                return pa.table([pa.array([], pa.int64()), pa.array([], pa.float64()), pa.array([], pa.list_(pa.float64()))], names=names)
            i = a["i"].to_numpy()
            deg, wv = product(i, matrix(a["xi"], len(a)), b["j"].to_numpy(), matrix(b["xj"], len(b)), matrix(b["v"], len(b)), sigma)
            return pa.table([pa.array(i), pa.array(deg), lists(wv)], names=names)

        parts = left.groupBy("bi", "bj").cogroup(right.groupBy("bi", "bj")).applyInArrow(part, "id long, deg double, wv array<double>")
        added = parts.groupBy("id").agg(F.sum("deg").alias("deg"), *vector_sum("wv", m)).select("id", "deg", as_vector(m, "wv"))
        return both.select("id", "v").join(added, "id").select(*_NAMES)


class SparseOp(Op):
    """Truncated graph, stored as edges: weights of at least ``theta``, or the ``knn`` nearest made symmetric.

    ``mode='exact'`` finds edges by comparing all blocks, up to ``max_pairs`` pairs; ``'lsh'``
    by random projections, at any size, which may miss some. ``edges`` takes a graph that is
    there already. They are found as they are read; the first product writes them once. Not for a released step.
    """

    def __init__(self, sigma: float, theta: float | None = 0.0, knn: int | None = None, mode: str = "exact", seed: int = 1, block: int = 4096, max_pairs: float = 1e12, edges: DataFrame | None = None):
        self.sigma, self.theta, self.knn, self.mode, self.seed, self.block, self.max_pairs, self.edges = sigma, theta, knn, mode, seed, block, max_pairs, edges
        self.written = edges is not None

    def prepare(self) -> None:
        if self.edges is not None:
            return
        if self.mode != "lsh":
            _check_pairs(self.points.count(), self.max_pairs)
        self.edges, self.written = self._knn() if self.knn else self._threshold(), False

    def _knn(self) -> DataFrame:
        v = self.points.select("id", F.col("x").alias("v"))
        near = knn(v, v, self.knn).select(F.col("query_id").alias("i"), F.col("match_id").alias("j"), F.exp(-F.col("dist") / self.sigma).alias("w"))
        return near.unionByName(near.select(F.col("j").alias("i"), F.col("i").alias("j"), "w")).groupBy("i", "j").agg(F.max("w").alias("w"))

    def _threshold(self) -> DataFrame:
        if self.mode == "lsh":
            from pyspark.ml.feature import BucketedRandomProjectionLSH
            from pyspark.ml.functions import array_to_vector, vector_to_array

            if not self.theta:
                raise ValueError("projections need theta > 0")
            radius = math.sqrt(-self.sigma * math.log(self.theta))
            p = self.points.select("id", "x", array_to_vector("x").alias("f"))
            lsh = BucketedRandomProjectionLSH(inputCol="f", outputCol="h", bucketLength=2 * radius, numHashTables=8, seed=self.seed).fit(p)
            hashed = lsh.transform(p).select("id", "x", F.transform("h", lambda z: vector_to_array(z)[0]).alias("h"))
            return self._met(hashed, radius + 1e-9)
        sigma, least = self.sigma, self.theta or 0.0

        def of(a: Arrays, b: Arrays | None) -> Iterator[Arrays]:
            for rows, cols, kept in patches(a, b):
                w = kept(_weights(rows, cols, sigma))
                at = np.flatnonzero(w >= least)
                i, j, w = kept(rows["id"][:, None])[at], kept(cols["id"][None])[at], w[at]
                yield {"i": i, "j": j, "w": w}
                yield {"i": j, "j": i, "w": w}

        return by_blocks(self.points, of, "i long, j long, w double", side=self.block)

    def _met(self, hashed: DataFrame, radius: float) -> DataFrame:
        """Edges of rows ``(id, x, h)`` within ``radius`` that share one of the buckets ``h`` at least.

        Buckets hold most rows where rows lie close, so blocks meet whole, once, and not
        bucket by bucket in each table; distances leave few pairs, whose buckets are compared.
        """
        sigma = self.sigma

        def of(a: Arrays, b: Arrays | None) -> Iterator[Arrays]:
            other = a if b is None else b
            if len(a["id"]) and len(other["id"]):
                for r, c, gap in within(a["x"], other["x"], radius):
                    keep = a["id"][r] != other["id"][c]
                    if b is None:
                        keep &= r < c
                    keep = np.flatnonzero(keep)
                    keep = keep[_share(a["h"], r[keep], other["h"], c[keep])]
                    i, j, w = a["id"][r[keep]], other["id"][c[keep]], np.exp(-gap[keep] / sigma)
                    yield {"i": i, "j": j, "w": w}
                    yield {"i": j, "j": i, "w": w}

        return by_blocks(hashed, of, "i long, j long, w double", "h")

    def apply(self, v: DataFrame | None) -> DataFrame:
        both = self._rows(v).select("id", "v")
        m = 1 if v is None else width(v)
        if not self.written:
            self.edges, self.written = cut(self.edges, "edges"), True
        e = self.edges.join(both.select(F.col("id").alias("j"), "v"), "j")
        sums = e.groupBy(F.col("i").alias("id")).agg(F.sum("w").alias("deg"), *(F.sum(F.col("w") * F.element_at("v", k + 1)).alias(f"_s{k}") for k in range(m)))
        none = F.lit(0.0)
        return known_width(both.join(sums, "id", "left").select("id", "v", F.coalesce("deg", none).alias("deg"), F.array(*(F.coalesce(f"_s{k}", none) for k in range(m))).alias("wv")), m)


class FeatureMapOp(Op):
    """Random cosine features z with z(x).z(y) about the kernel: two passes, no pair of rows ever meets.

    Pass 1 sums z v' and z over all rows (R x (m + 1) numbers a task, added up by Spark);
    pass 2 maps each row. The error falls as 1 / sqrt(R), fastest for wide kernels. Directions
    come from the portable source, so any engine can repeat them. Not for a released step.
    """

    def __init__(self, sigma: float, features: int = 256, seed: int | str = 1):
        self.sigma, self.features, self.seed = sigma, features, seed

    def prepare(self) -> None:
        d = width(self.points, "x")
        self.omega = math.sqrt(2.0 / self.sigma) * normals(f"{self.seed}w", np.arange(d), self.features)
        self.phase = 2 * math.pi * uniforms(f"{self.seed}p", self.features)

    def _z(self) -> Callable[[np.ndarray], np.ndarray]:
        omega, phase, scale = self.omega, self.phase, math.sqrt(2.0 / self.features)
        return lambda x: scale * np.cos(x @ omega + phase)

    def apply(self, v: DataFrame | None) -> DataFrame:
        z, rows = self._z(), self._rows(v)
        m = width(rows)

        def sums(b: pa.RecordBatch) -> np.ndarray:
            return z(matrix(b.column(0), b.num_rows)).T @ np.c_[matrix(b.column(1), b.num_rows), np.ones(b.num_rows)]

        sent = rows.sparkSession.sparkContext.broadcast(summed(rows.select("x", "v"), sums, self.features, m + 1))

        def multiply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                n = b.num_rows
                if n:
                    f, vv = z(matrix(b.column(1), n)), matrix(b.column(2), n)
                    own = (f * f).sum(1)
                    both = f @ sent.value
                    yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(both[:, -1] - own), lists(both[:, :-1] - own[:, None] * vv)], _NAMES)

        return known_width(rows.select("id", "x", "v").mapInArrow(multiply, PRODUCT), m)


def laplacian_product(op: Op, v: DataFrame) -> DataFrame:
    """``(id, v, deg, lv)``: L V = D V - W V."""
    return op.apply(v).select("id", "v", "deg", F.zip_with("v", "wv", lambda a, b: a * F.col("deg") - b).alias("lv"))


def energy(v: DataFrame, op: Op) -> float:
    """tr(V' L V): the sum over unordered pairs of weight times squared gap."""
    p = laplacian_product(op, v)
    return p.agg(F.sum(F.aggregate(F.zip_with("v", "lv", lambda a, b: a * b), F.lit(0.0), lambda s, z: s + z))).first()[0] or 0.0
