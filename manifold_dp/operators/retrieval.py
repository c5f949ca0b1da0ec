"""Dummies, party sets, bucketed neighbours and the whole client-server exchange."""

from __future__ import annotations

from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import dist2
from ..sources import cut, drop, known_width, local
from . import align
from .kernel import DenseOp, Op
from .ledger import Book
from .neighbours import FOUND, block, cells, every, knn, matrix, near_of
from .release import Barrier, ReleaseReport, free_steps, noisy_first_step, published_labels, resume
from .step import run, run_many

#: Public rows of a class among which one target's dummy is chosen, about.
CHOICE = 64


def _hashed(*parts: Column | str) -> Column:
    return F.md5(F.concat_ws(":", *(F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts)))


def _drawn(parts: Column, of: Column) -> Column:
    """The hash ``of`` as a number below ``parts``."""
    return F.conv(F.substring(of, 1, 8), 16, 10).cast("long") % parts


def dummies(target: DataFrame, public: DataFrame, seed: int | str = 1, choice: int = CHOICE) -> DataFrame:
    """For each target one public row of every class but its own, by least hash of (seed, target, row).

    ``(target_id, id, x, label)``: with the target itself, every class is queried once. Rows
    of a class of 2 x ``choice`` and more are dealt into groups of about ``choice`` by hash; a target
    draws one group and looks at its rows only, so targets never meet all public rows. If
    a drawn group is empty, which is next to impossible, all rows of its class are looked at.
    """
    s = str(seed)
    sizes = local(public.where("label IS NOT NULL").groupBy("label").agg(F.greatest(F.lit(1), F.floor(F.count(F.lit(1)) / choice)).alias("_groups")))
    rows = public.select("id", "x", "label").join(sizes, "label").withColumn("_g", _drawn(F.col("_groups"), _hashed(s, "group", F.col("id"))))
    asked = target.select(F.col("id").alias("target_id"), F.col("label").alias("_own")).join(sizes, F.col("label") != F.col("_own"))
    asked = asked.select("target_id", "label", _drawn(F.col("_groups"), _hashed(s, "draw", F.col("target_id"), F.col("label"))).alias("_g"))
    w = Window.partitionBy("target_id", "label").orderBy(_hashed(s, F.col("target_id"), F.col("id")), "id")

    def first(df: DataFrame) -> DataFrame:
        return df.withColumn("_r", F.row_number().over(w)).where("_r = 1").select("target_id", "id", "x", "label")

    found = first(asked.join(rows, ["label", "_g"]))
    missing = asked.join(found.select("target_id", "label"), ["target_id", "label"], "left_anti")
    return found.unionByName(first(missing.join(rows.drop("_g"), "label"))) if missing.head(1) else found


def client_set(target: DataFrame, public: DataFrame, dummy: DataFrame, keep_dummy_anchor: bool = False) -> DataFrame:
    """Targets, dummies and public anchors, with roles. Dummies are left out of the anchors, or with ``keep_dummy_anchor`` stand in both under ids of their own (negative)."""
    d = dummy.select("id", "x", "label").distinct()
    anchors = public.select("id", "x", "label").withColumn("role", F.lit("public"))
    if keep_dummy_anchor:
        d = d.withColumn("id", -F.col("id") - 1)
    else:
        anchors = anchors.join(d.select("id"), "id", "left_anti").select("id", "x", "label", "role")
    return target.select("id", "x", "label").withColumn("role", F.lit("target")).unionByName(d.withColumn("role", F.lit("dummy"))).unionByName(anchors)


def server_set(server: DataFrame, public: DataFrame) -> DataFrame:
    return server.select("id", "x", "label").withColumn("role", F.lit("server")).unionByName(public.select("id", "x", "label").withColumn("role", F.lit("public")))


def knn_buckets(queries: DataFrame, rows: DataFrame, k: int, centroids: int = 16, probes: int = 4, seed: int = 1) -> DataFrame:
    """Approximate: rows are dealt to their nearest of ``centroids`` sampled rows, queries look into ``probes`` of them."""
    c = rows.orderBy(_hashed(str(seed), F.col("id"))).limit(centroids)
    centres = local(c.agg(F.collect_list(F.struct(F.col("id").alias("c"), F.col("v").alias("cv"))).alias("_centres")))  # ``centroids`` rows

    def nearest(df: DataFrame, n: int) -> DataFrame:
        gaps = F.transform("_centres", lambda z: F.struct(F.round(dist2(F.col("v"), z["cv"]), 12).alias("g"), z["c"].alias("c")))
        near = F.transform(F.slice(F.array_sort(gaps), 1, n), lambda z: z["c"])
        return df.select("id", "v").crossJoin(centres).select("id", "v", F.explode(near).alias("bucket"))

    q, s = nearest(queries, probes), nearest(rows, 1)
    n, of = queries.count(), s.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    parts = cells(n * probes // max(1, centroids), of, 1)
    q = q.select(F.col("id").alias("qid"), F.col("v").alias("qv"), F.col("bucket").alias("qbucket"), block(F.col("id"), parts[0]).alias("qb"), every(parts[1]).alias("rb"))
    s = s.select(F.col("id").alias("rid"), F.col("v").alias("rv"), F.col("bucket").alias("rbucket"), block(F.col("id"), parts[1]).alias("rb"), every(parts[0]).alias("qb"))

    def meet(a: pa.Table, b: pa.Table) -> pa.Table:
        return near_of(a["qid"].to_numpy(), matrix(a["qv"], len(a)), b["rid"].to_numpy(), matrix(b["rv"], len(b)), k)

    w = Window.partitionBy("query_id").orderBy("dist", "match_id")
    near = q.groupBy("qbucket", "qb", "rb").cogroup(s.groupBy("rbucket", "qb", "rb")).applyInArrow(meet, FOUND)
    return near.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def parse(matches: DataFrame, ids: DataFrame) -> DataFrame:
    """The client keeps the answers to its targets."""
    return matches.join(ids.select(F.col("id").alias("query_id")), "query_id", "left_semi")


@dataclass
class Config:
    """Settings of the exchange."""

    m: int = 16
    sigma: float = 4.0
    alpha: float = 0.1
    epsilon: float = 1.0
    delta: float = 1e-5
    steps: int = 5
    server_steps: int | None = None
    sigma_q: float = 1.0
    seed: int | str = 1
    server_seed: int | str | None = None
    form: str = "row_split"
    calibration: str = "analytic"
    rebuild: str = "once"
    renorm: str = "rows"
    label_policy: str = "masked"
    label_epsilon: float | None = None
    padding: str = "reserve"
    align: str = "rigid"
    keep_dummy_anchor: bool = False
    private: bool = True
    test_noise: int | str | None = None
    op: Op | None = None
    book: Book | None = None


@dataclass
class Exchange:
    """What an exchange produced: answers to the targets, all answers, both embeddings and the report."""

    answers: DataFrame
    matches: DataFrame
    client: DataFrame
    server: DataFrame
    report: ReleaseReport | None
    rmsd_before: float
    rmsd_after: float
    spread: float


@dataclass
class Served:
    """What the server has ready for any client: its embedding, and the ids of its anchors and of the rows it searches."""

    v: DataFrame
    anchors: DataFrame
    base: DataFrame


def _servers(cfg: Config) -> tuple[int, int | str]:
    return cfg.server_steps if cfg.server_steps is not None else cfg.steps, cfg.server_seed if cfg.server_seed is not None else f"{cfg.seed}s"


def serve_many(server: DataFrame, public: DataFrame, cfgs: list[Config]) -> list[Served]:
    """``serve`` for settings that differ in alpha and seed alone: one graph serves them all."""
    theirs, (cfg, *others) = server_set(server, public), cfgs
    same = [(c.m, c.sigma, c.sigma_q, _servers(c)[0]) for c in cfgs]
    if cfg.op is not None or any(s != same[0] or c.op is not None for s, c in zip(same[1:], others, strict=True)):
        raise ValueError("one graph serves settings of one m, sigma, start and number of steps, by the dense product")
    anchors, base = (theirs.where(f"role = '{r}'").select("id") for r in ("public", "server"))
    return [Served(v, anchors, base) for v in run_many(theirs, cfg.m, cfg.sigma, [(c.alpha, _servers(c)[1]) for c in cfgs], same[0][3], cfg.sigma_q)]


def serve(server: DataFrame, public: DataFrame, cfg: Config) -> Served:
    """The server's own steps, from the raw features of its rows and the public ones."""
    theirs = server_set(server, public)
    steps, seed = _servers(cfg)
    v = run(theirs, cfg.m, cfg.sigma, cfg.alpha, steps, seed, cfg.op or DenseOp(cfg.sigma, single=True), sigma_q=cfg.sigma_q, rescale=True).v
    return Served(v, theirs.where("role = 'public'").select("id"), theirs.where("role = 'server'").select("id"))


def private_retrieve(target: DataFrame, public: DataFrame, server: DataFrame, k: int = 8, cfg: Config | None = None, served: Served | None = None) -> Exchange:
    """The client's noisy release and free steps, the server's own steps, alignment on anchors, retrieval for all, parsing by the client.

    The client writes its book of ids and the labels that later steps may read before the
    release; behind the barrier only those and the release are read. ``served``: a server
    embedding that is there already.
    """
    cfg = cfg or Config()
    dummy = dummies(target, public, cfg.seed)
    mine = client_set(target, public, dummy, cfg.keep_dummy_anchor)
    report = None
    if cfg.private:
        mine = cut(mine, "client")  # the client's own, gone before the barrier
        ids = cut(mine.select("id", "role"), "ids")
        labels, said, cost = published_labels(mine, cfg.label_policy, cfg.label_epsilon, cfg.book)
        out, report = noisy_first_step(mine, cfg.m, cfg.sigma, cfg.alpha, cfg.epsilon, cfg.delta, cfg.sigma_q, cfg.seed, cfg.form, cfg.calibration, padding=cfg.padding, book=cfg.book, test_noise=cfg.test_noise)
        report.label_policy, report.epsilon, report.assumptions = cfg.label_policy, report.epsilon + cost, report.assumptions + said
        drop(target.sparkSession, mine)
        barrier = Barrier(out.at, labels.at, ids.at)
        v = free_steps(resume(target.sparkSession, out.at), labels, cfg.m, cfg.sigma, 0.0 if cfg.label_policy == "off" else cfg.alpha, cfg.steps, cfg.rebuild, cfg.renorm, cfg.op, barrier=barrier)
    else:
        ids = mine.select("id", "role")
        v = run(mine, cfg.m, cfg.sigma, cfg.alpha, cfg.steps + 1, cfg.seed, cfg.op or DenseOp(cfg.sigma, single=True), sigma_q=cfg.sigma_q, rescale=True).v
    served = served or serve(server, public, cfg)
    s = served.v
    anchors = served.anchors.join(ids.where("role = 'public'").select("id"), "id")
    a, b = (known_width(x.join(anchors, "id", "left_semi"), cfg.m) for x in (v, s))
    before = align.rmsd(a, b)
    if cfg.align != "none":
        motion = align.fit(a, b, scale=cfg.align == "similarity", reflect=cfg.align == "orthogonal")
        v, a = align.apply(v, motion), align.apply(a, motion)
    after = align.rmsd(a, b)
    asked = v.join(ids.where("role IN ('target', 'dummy')").select("id"), "id", "left_semi")
    if cfg.private:
        barrier.check(asked)
    matches = knn(asked, s.join(served.base, "id", "left_semi"), k, skip_self=False)
    return Exchange(parse(matches, ids.where("role = 'target'")), matches, v, s, report, before, after, align.spread(b))


__all__ = ["Config", "Exchange", "Served", "client_set", "dummies", "knn", "knn_buckets", "parse", "private_retrieve", "serve", "serve_many", "server_set"]
