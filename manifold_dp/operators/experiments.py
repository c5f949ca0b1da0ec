"""The experiment workloads on stand-in feature sets. Each returns a table of measures.

Sweeps of many settings and seeds run as ``sweep``: each run in one task, on whole sets.
"""

from __future__ import annotations

import json
import math
import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import cut, known_width
from . import arrays, baselines, features, metrics, noise, retrieval, sensitivity
from .kernel import DenseOp, FeatureMapOp, SparseOp
from .neighbours import matrix
from .release import free_steps, labels_for, release_then_iterate
from .step import run
from .sweep import LINEAR, Held, fits, fits_linear, sweep

#: Rows of the largest product that is timed, and of the largest that compares all pairs.
LARGEST, LARGEST_DENSE = 1_000_000, 32_000
#: Methods that draw no noise: equal settings give equal results.
FIXED = ("raw", "pca", "tsne", "contrast", "trace")
SETS = ("emb_planted", "doc_lang", "page_lang")
#: Rows of a set beyond which t-SNE and private SNE are not done in one task: they hold tables of pairs.
PLACED = 4000


def points_of(spark: SparkSession, sf_dir: str, name: str, rows: int | None = None) -> DataFrame:
    """A set, written once: all of it, or for trials the ``rows`` of least hash of the id. Registered queries take all."""
    p = features.feature_set(spark, sf_dir, name)
    if rows is not None:
        p = p.orderBy(F.md5(F.concat_ws(":", F.lit("rows"), F.col("id").cast("string"))), "id").limit(rows)
    return cut(p, name)


def _recalls(v: DataFrame, points: DataFrame, ks=(1, 8), every: int = 1) -> dict:
    """Of rows whose id is divisible by ``every``, among all others."""
    got = metrics.recall_table(retrieval.knn(v.where(F.col("id") % every == 0) if every > 1 else v, v, max(ks)), points, ks).collect()
    return {f"recall_at_{r.k}": r.recall for r in got} | {f"precision_at_{r.k}": r.precision for r in got}


def _table(spark: SparkSession, rows: list[dict], names: list[str] | None = None) -> DataFrame:
    names = names or list(dict.fromkeys(k for r in rows for k in r))
    kinds = {n: "string" if any(isinstance(r.get(n), str) for r in rows) else "long" if all(isinstance(r.get(n), int) for r in rows) else "double" for n in names}
    cast = {"string": lambda x: None if x is None else str(x), "long": int, "double": lambda x: None if x is None else float(x)}
    return spark.createDataFrame([tuple(cast[kinds[n]](r.get(n)) for n in names) for r in rows], ", ".join(f"`{n}` {kinds[n]}" for n in names))


def _config(a: dict) -> retrieval.Config:
    return retrieval.Config(m=a["m"], sigma=a["sigma"], alpha=a["alpha"], epsilon=a["epsilon"] or 1.0, delta=a.get("delta", 1e-5), private=a["epsilon"] is not None, steps=a["steps"], seed=a["seed"])


def _hosts(sets: dict[str, DataFrame], arms: list[dict]) -> dict[str, retrieval.Served]:
    """The server's embedding for each exchange, by ``_host``: it knows no epsilon, and those on one graph are made together."""
    graphs: dict[tuple, dict[str, dict]] = {}
    for a in arms:
        graphs.setdefault((a["set"], a["m"], a["sigma"], a["steps"]), {})[_host(a)] = a
    out: dict[str, retrieval.Served] = {}
    for (name, *_), by in graphs.items():
        p = sets[name]
        out |= zip(by, retrieval.serve_many(p.where("role = 'server'"), p.where("role = 'public'"), [_config(a) for a in by.values()]), strict=True)
    return out


def _host(a: dict) -> str:
    return json.dumps([a[n] for n in ("set", "m", "sigma", "steps", "alpha", "seed")])


def _distributed(p: DataFrame, a: dict, served: retrieval.Served | None = None) -> list[dict]:
    """What ``sweep.measures`` gives, by the distributed operators."""
    m, seed, method = a.get("m", 16), a.get("seed", 1), a["method"]
    if method == "exchange":
        x = _exchange(p, _config(a), served=served)
        return [{"rmsd_before": x.rmsd_before, "rmsd_after": x.rmsd_after, "relative_after": x.rmsd_after / max(x.spread, 1e-300), "precision_at_8": metrics.precision_at(x.answers, p, 8), "recall_at_8": metrics.recall_at(x.answers, p, 8)}]
    if method == "trace":
        r = run(p, m, a["sigma"], a["alpha"], a["steps"], seed, rescale=True, keep=True, monitor=True)
        return [{**r.log[t], "objective": r.log[t]["objective"] * math.exp(2 * r.log[t]["log_scale"]), **_recalls(v, p)} for t, v in enumerate(r.steps)]
    true = p
    if (fold := a.get("fold")) is not None:
        of = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit("fold"), F.col("id").cast("string"))), 1, 8), 16, 10).cast("long") % a["folds"]
        p = p.withColumn("label", F.when(of != fold, F.col("label")))
    if method == "raw":
        v = baselines.raw(p)
    elif method == "pca":
        v = baselines.pca(p, m)
    elif method == "tsne":
        v = baselines.tsne(p, 2, 30, a["iterations"], seed=seed)
    elif method == "contrast":
        v = run(p, m, a["sigma"], a["alpha"], a["steps"], seed, rescale=True).v
    elif method == "release":
        v = release_then_iterate(p, m, a["sigma"], a["alpha"], a["epsilon"], a["delta"], a["steps"], label_policy=a["policy"], form=a.get("form", "row_split"), calibration="analytic", seed=seed)[0]
    elif method == "pure_noise":
        labels = cut(labels_for(p, a["policy"])[0], "labels")
        v = free_steps(baselines.pure_noise(p, m, seed), labels, m, a["sigma"], 0.0 if a["policy"] == "off" else a["alpha"], a["steps"])
    elif method == "dp_pca":
        v = baselines.dp_pca(p, m, a["epsilon"], a["delta"])
    elif method == "dp_rp":
        v = baselines.dp_rp(p, m, a["epsilon"], a["delta"], seed)
    else:
        v = baselines.dp_sne(p, 2, a["epsilon"], a["delta"], iterations=a["iterations"], seed=seed)
    if fold is not None:
        asked = v.join(true.where(of == fold).select("id"), "id", "left_semi")
        got = metrics.recall_table(retrieval.knn(asked, v, 8), true, (1, 8)).collect()
        return [{f"recall_at_{r.k}": r.recall for r in got} | {f"precision_at_{r.k}": r.precision for r in got}]
    out = _recalls(v, p, every=a.get("every", 1))
    if a.get("targets"):
        got = metrics.recall_table(retrieval.knn(v.join(p.where("role = 'target'").select("id"), "id", "left_semi"), v, 8), p, (1, 8)).collect()
        out |= {f"target_recall_at_{r.k}": r.recall for r in got} | {f"target_precision_at_{r.k}": r.precision for r in got}
    return [out]


def _placed(sets: dict[str, DataFrame], arms: list[dict]) -> dict[str, np.ndarray]:
    """Places in the plane by the distributed operators, by the arm's key: all private SNE runs of a set go round by round together."""
    out: dict[str, DataFrame] = {}
    together: dict[tuple, list[dict]] = {}
    for a in arms:
        if a["method"] == "tsne":
            out[a["key"]] = baselines.tsne(sets[a["set"]], 2, 30, a["iterations"], seed=a["seed"])
        else:
            together.setdefault((a["set"], a["delta"], a["iterations"]), []).append(a)
    for (name, delta, iterations), some in together.items():
        out |= zip((a["key"] for a in some), baselines.dp_sne_many(sets[name], 2, [(a["epsilon"], a["seed"]) for a in some], delta, iterations=iterations), strict=True)
    tables = {key: v.select("id", "v").toArrow().sort_by("id") for key, v in out.items()}
    return {key: matrix(t["v"], len(t)) for key, t in tables.items()}


def measured(spark: SparkSession, sets: dict[str, DataFrame], arms: list[dict]) -> list[dict]:
    """Each arm with its measures: those of sets that one task can hold as a sweep, the others run by run."""
    small = {name: p for name, p in sets.items() if fits({name: p})}
    if not fits(small):
        small = {}
    busy = spark.sparkContext.defaultParallelism
    many = {name: p for name, p in sets.items() if name not in small and sum(a["set"] == name and a["method"] in LINEAR for a in arms) >= 2 * busy and fits_linear({name: p})}
    if not fits_linear(small | many):
        many = {}
    counts = {name: p.count() for name, p in (small | many).items()}
    first: dict[str, dict] = {}  # runs without noise that differ in nothing but what a search moves are one
    of = [json.dumps({n: x for n, x in a.items() if n != "moved"} | ({} if a["method"] in FIXED else {"arm": i}), sort_keys=True) for i, a in enumerate(arms)]
    for key, a in zip(of, arms, strict=True):
        first.setdefault(key, a | {"key": key})
    apart = [a for a in first.values() if a["method"] in ("tsne", "dp_sne") and counts.get(a["set"], 0) > PLACED]
    swept = [a for a in first.values() if a["set"] in small or (a["set"] in many and a["method"] in LINEAR)]
    swept += [a for a in apart if a not in swept]
    got = sweep(spark, small | many, swept, _placed(sets, apart)) if swept else []
    large = [a for a in first.values() if a not in swept]
    hosts = _hosts(sets, [a for a in large if a["method"] == "exchange"])
    for a in large:
        served = {"served": hosts[_host(a)]} if a["method"] == "exchange" else {}
        got += [a | row for row in _distributed(sets[a["set"]], a, **served)]
    rows: dict[str, list[dict]] = {}
    for r in got:
        rows.setdefault(r.pop("key"), []).append(r)
    return [r | a for key, a in zip(of, arms, strict=True) for r in rows[key]]


def class_picture(spark: SparkSession, sf_dir: str, steps: int = 3, m: int = 2, sigma: float = 0.1, alphas: tuple[float, ...] = (0.0, 0.1)) -> DataFrame:
    """Coordinates after three steps, and how far classes part before and after, without and with the label term (W1)."""
    p = points_of(spark, sf_dir, "emb_planted")
    out = None
    for alpha in alphas:
        r = run(p, m, sigma, alpha, steps, rescale=True, keep=True)
        start, end = (metrics.separation(v, p) for v in (r.steps[0], r.v))
        rows = r.v.join(p.select("id", "label"), "id")
        rows = rows.select("id", "label", F.lit(alpha).alias("alpha"), F.element_at("v", 1).alias("x1"), F.element_at("v", 2).alias("x2"), F.lit(start).alias("separation_start"), F.lit(end).alias("separation_end"))
        out = rows if out is None else out.unionByName(rows)
    return out


def convergence(spark: SparkSession, sf_dir: str, steps: int = 10, sigma: float = 0.1, alpha: float = 0.0, sets: tuple[str, ...] = SETS, m: int = 16) -> DataFrame:
    """Recall and objective by iteration (W2)."""
    arms = [{"set": name, "method": "trace", "m": m, "sigma": sigma, "alpha": alpha, "steps": steps, "seed": 1} for name in sets]
    rows = measured(spark, {n: points_of(spark, sf_dir, n) for n in sets}, arms)
    return _table(spark, rows, ["set", "t", "objective", "log_scale", "recall_at_1", "precision_at_1", "recall_at_8", "precision_at_8"]).withColumn("t", F.col("t").cast("long"))


def grid(
    spark: SparkSession,
    sf_dir: str,
    ms=(2, 4, 8, 16, 32),
    alphas=(0.0, 0.05, 0.1, 0.5, 1.0),
    sigmas=(0.05, 0.1, 0.25, 1.0, 4.0),
    private: bool = False,
    name: str = "emb_planted",
    base=(16, 0.1, 0.1),
    epsilon: float = 10.0,
    steps: int = 5,
    rows: int | None = None,
    folds: int = 5,
) -> DataFrame:
    """One parameter moved at a time around ``base`` (m, alpha, sigma): recall of held-out folds, whose labels are hidden (W3).

    A search on secret rows would spend budget, so it is one over rows whose labels are public.
    """
    p = points_of(spark, sf_dir, name, rows)
    m0, a0, s0 = base
    todo = [("m", m, a0, s0) for m in ms] + [("alpha", m0, a, s0) for a in alphas] + [("sigma", m0, a0, s) for s in sigmas]
    how = {"method": "release", "policy": "public", "epsilon": epsilon, "delta": 1e-5} if private else {"method": "contrast"}
    arms = [{"set": name, "moved": what, "m": m, "alpha": a, "sigma": s, "steps": steps, "fold": f, "folds": folds, "seed": 1, "private": int(private)} | how for what, m, a, s in todo for f in range(folds)]
    by = ["moved", "m", "alpha", "sigma", "private"]
    return metrics.curve(_table(spark, measured(spark, {name: p}, arms), [*by, "recall_at_8", "precision_at_8"]), by, ("recall_at_8", "precision_at_8")).withColumnRenamed("seeds", "folds")


def choice(spark: SparkSession, sf_dir: str, **grid_args) -> DataFrame:
    """The value of each parameter with the best held-out precision; of equal ones the first by value."""
    g = grid(spark, sf_dir, **grid_args)
    value = F.when(F.col("moved") == "m", F.col("m").cast("double")).when(F.col("moved") == "alpha", F.col("alpha")).otherwise(F.col("sigma"))
    best = g.groupBy("moved").agg(F.max(F.struct(F.round("precision_at_8_mean", 9).alias("p"), (-value).alias("v"))).alias("b"))
    return best.select("moved", (-F.col("b.v")).alias("value"), F.col("b.p").alias("precision_at_8"))


def privacy_utility(spark: SparkSession, sf_dir: str, epsilons=(0.1, 0.5, 1.0, 5.0, 10.0, 100.0, 1000.0), sets=SETS, seeds=(1, 2, 3, 4, 5), m: int = 16, sigma: float = 4.0, alpha: float = 0.1, delta: float = 1e-5, steps: int = 5, rows: int | None = None, sne: bool = True) -> DataFrame:
    """Recall and precision at 8 by epsilon, method and set, mean and spread over seeds, with the controls beside them (W4, W9).

    Releases run at ``sigma``, where the noise is least, and at a narrow kernel with more weight on
    labels (``_narrow``), where the map serves retrieval and public labels carry it.
    """
    points = {n: points_of(spark, sf_dir, n, rows) for n in sets}
    narrow = {"sigma": 0.1, "alpha": 0.5, "setting": "narrow"}
    same = {"m": m, "sigma": sigma, "alpha": alpha, "delta": delta, "steps": steps, "epsilon": None, "targets": True}
    arms = []
    for name in sets:
        add = lambda method, seed=1, name=name, **kw: arms.append({"set": name, "method": method, "seed": seed, **same, **kw})
        add("tsne", iterations=150)
        add("raw")
        add("pca")
        for seed in seeds:
            add("contrast", seed, sigma=0.1, alpha=0.0, steps=7)
            for policy in ("public", "off", "masked"):
                add("pure_noise", seed, policy=policy)
                add("pure_noise", seed, policy=policy, **narrow)
        for eps in epsilons:
            for seed in seeds:
                for policy in ("public", "masked"):
                    add("release", seed, epsilon=eps, policy=policy)
                    add("release", seed, epsilon=eps, policy=policy, **narrow)
                add("dp_pca", seed, epsilon=eps)
                add("dp_rp", seed, epsilon=eps)
                if sne:
                    add("dp_sne", seed, epsilon=eps, iterations=10)
    got = [r | {"method": "_".join([r["method"], *(r[k] for k in ("policy", "setting") if k in r)])} for r in measured(spark, points, arms)]
    by, values = ["set", "method", "epsilon"], ("recall_at_8", "precision_at_8", "target_precision_at_8")
    return metrics.curve(_table(spark, got, [*by, *values]), by, values)


def alignment(spark: SparkSession, sf_dir: str, epsilons=(1.0, 100.0, 1e4, 1e6), alpha: float = 0.5, rows: int | None = None, seeds=(1, 2, 3, 4, 5), sigma: float = 4.0, m: int = 16, steps: int = 5, name: str = "emb_planted") -> DataFrame:
    """Anchor distance before and after alignment, and target precision, by epsilon (none: without noise), mean and spread over seeds (W5)."""
    p = points_of(spark, sf_dir, name, rows)
    arms = [{"set": name, "method": "exchange", "m": m, "sigma": sigma, "alpha": a, "steps": steps, "delta": 1e-5, "epsilon": e, "seed": s} for e in (*epsilons, None) for a in sorted({0.0, alpha}) for s in seeds]
    by, values = ["epsilon", "alpha"], ("rmsd_before", "rmsd_after", "relative_after", "precision_at_8")
    return metrics.curve(_table(spark, measured(spark, {name: p}, arms), [*by, *values]), by, values)


def _exchange(p: DataFrame, cfg: retrieval.Config, k: int = 8, served: retrieval.Served | None = None) -> retrieval.Exchange:
    return retrieval.private_retrieve(p.where("role = 'target'"), p.where("role = 'public'"), p.where("role = 'server'"), k, cfg, served)


def end_to_end(spark: SparkSession, sf_dir: str, name: str = "emb_planted", cfg: retrieval.Config | None = None, k: int = 8, rows: int | None = None) -> DataFrame:
    """The whole exchange: the answers each target's client keeps, and whether they have the target's label (W6)."""
    p = points_of(spark, sf_dir, name, rows)
    answers = _exchange(p, cfg or retrieval.Config(), k).answers
    own, match = p.select(F.col("id").alias("query_id"), F.col("label").alias("_q")), p.select(F.col("id").alias("match_id"), F.col("label").alias("_m"))
    return answers.join(own, "query_id").join(match, "match_id").select("query_id", "match_id", "rank", F.col("_q").eqNullSafe(F.col("_m")).cast("int").alias("hit"))


def growing(n: int) -> tuple[int, ...]:
    """Copies of n rows: 1, 4, 16 and so on, and what makes ``LARGEST`` rows."""
    most = max(1, LARGEST // max(n, 1))
    return (*(4**i for i in range(most.bit_length()) if 4**i < most), most)


def _shuffled(spark: SparkSession) -> int:
    """Bytes this session has written to shuffles so far."""
    every = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    return sum(every.apply(i).totalShuffleWrite() for i in range(every.size()))


def _copies(base: DataFrame, graph: DataFrame, c: int, m: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Points, an embedding and edges of c copies. Spark takes them for as small as their base: hints keep it from sending them whole."""
    copy = F.explode(F.sequence(F.lit(0), F.lit(c - 1)))
    p = base.withColumn("c", copy).select((F.col("id") * c + F.col("c")).alias("id"), "x").hint("merge")
    v = known_width(p.select("id", F.array(*(F.randn(k) for k in range(m))).alias("v")), m)
    return p, v, graph.withColumn("c", copy).select((F.col("i") * c + F.col("c")).alias("i"), (F.col("j") * c + F.col("c")).alias("j"), "w").hint("merge")


def cost(spark: SparkSession, sf_dir: str, copies: tuple[int, ...] | None = None, m: int = 16, sigma: float = 4.0, neighbours: int = 8, features_: int = 64) -> DataFrame:
    """Seconds and shuffled bytes of one product by operator and rows, the graph given (W7).

    Ids are multiplied, so features stay real, and the sparse graph is that of one copy in
    each. Without ``copies`` rows grow fourfold up to ``LARGEST``. The dense product, which
    compares all pairs, stops at ``LARGEST_DENSE`` rows: its cost is what the others avoid.
    ``terms``: pairs, edges, or rows times features that a product adds up.
    """
    base = points_of(spark, sf_dir, "emb_planted")
    n = base.count()
    graph = cut(SparseOp(sigma, knn=neighbours).over(base).edges, "edges")
    edges = graph.count()
    tasks = 2 * spark.sparkContext.defaultParallelism  # one small file each would be one task
    base, graph = base.repartition(tasks, "id"), graph.repartition(tasks, "i", "j")
    out = []
    for c in copies or growing(n):
        p, v, e = _copies(base, graph, c, m)
        ops = {"feature_map": (FeatureMapOp(sigma, features_), n * c * features_), "sparse_knn": (SparseOp(sigma, knn=neighbours, edges=e), edges * c)}
        if n * c <= LARGEST_DENSE:
            ops["dense"] = (DenseOp(sigma), (n * c) ** 2)
        for name, (op, terms) in ops.items():
            began, before = time.time(), _shuffled(spark)
            bound = op.over(p)
            built = time.time()
            bound.apply(v).agg(F.sum("deg"), F.sum(F.element_at("wv", 1))).first()
            out.append({"op": name, "rows": n * c, "terms": terms, "build_s": built - began, "product_s": time.time() - built, "shuffle_bytes": _shuffled(spark) - before})
    return _table(spark, out)


def null_controls(spark: SparkSession, sf_dir: str, m: int = 16, rows: int | None = None) -> DataFrame:
    """Sets whose labels carry no signal: every method must stay at chance (W8). Every row is searched for among all others."""
    points = {n: points_of(spark, sf_dir, n, rows) for n in ("emb_raw", "cust_profile")}
    chance = {}
    for name, p in points.items():
        shares = [r.n for r in p.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()]
        chance[name] = sum(s * s for s in shares) / sum(shares) ** 2
    arms = [{"set": n, "chance": chance[n], "m": m, "sigma": 0.1, "alpha": 0.0, "steps": 7, "method": method} for n in points for method in ("raw", "contrast", "pca")]
    return _table(spark, measured(spark, points, arms), ["set", "method", "chance", "recall_at_8", "precision_at_8"])


def membership_attack(spark: SparkSession, sf_dir: str, epsilons=(0.5, 1.0, 5.0, 50.0), draws: int = 400, m: int = 4, sigma: float = 4.0, alpha: float = 0.1, delta: float = 1e-5) -> DataFrame:
    """Releases of a set with and without one row, told apart by whoever knows all other rows and the start matrix.

    The score is the release's part along the known difference. ``advantage`` is measured,
    ``limit`` is the most that (epsilon, delta) allows.
    """
    held = Held.of(points_of(spark, sf_dir, "emb_planted"))
    without = held.take(np.arange(len(held.ids) - 1))
    q = arrays.normals(1, held.ids, m)
    a, b = (np.r_[arrays.step(q[: len(h.ids)], arrays.Graph(h.x, sigma), h.label, alpha, sigma), q[len(h.ids) :]] for h in (held, without))
    gap, rng, out = a - b, np.random.default_rng(), []
    norms = sensitivity.StartNorms(float(np.linalg.norm(q[:-1])), float(np.linalg.norm(q)))
    for eps in epsilons:
        tau = noise.calibrate(eps, delta, sensitivity.bound(len(without.ids), alpha, sigma, norms, "row_split"), "analytic")
        scores = [[float(((x + rng.normal(0, tau, x.shape) - b) * gap).sum()) for _ in range(draws)] for x in (a, b)]
        out.append({"epsilon": eps, "advantage": metrics.membership(*scores), "limit": (math.exp(eps) - 1 + 2 * delta) / (math.exp(eps) + 1)})
    return _table(spark, out)


def label_leak(spark: SparkSession, sf_dir: str, m: int = 16, sigma: float = 0.1, alpha: float = 0.5, steps: int = 5, name: str = "emb_planted", seeds=(1, 2, 3, 4, 5)) -> DataFrame:
    """Steps from pure noise by label policy: what public labels alone bring, and that masked ones bring nothing (W9)."""
    p = points_of(spark, sf_dir, name)
    arms = [{"set": name, "method": "pure_noise", "policy": policy, "m": m, "sigma": sigma, "alpha": alpha, "steps": steps, "seed": s, "targets": True} for policy in ("public", "masked", "off") for s in seeds]
    values = ("precision_at_8", "target_precision_at_8")
    return metrics.curve(_table(spark, measured(spark, {name: p}, arms), ["policy", *values]), ["policy"], values)
