"""The noisy first step, and the free iterations that read only what it released."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import unit
from ..sources import EMBED, cut, known_width
from . import noise, sensitivity
from .kernel import DenseOp, Op
from .labels import LabelOp
from .ledger import Book
from .step import contrast_step, run

LABEL_POLICIES = ("public", "masked", "randomized", "off")


@dataclass
class ReleaseReport:
    """What a release promises, and on which assumptions."""

    epsilon: float
    delta: float
    sensitivity: float
    tau: float
    n: int
    form: str
    calibration: str
    label_policy: str = "public"
    assumptions: list[str] = field(default_factory=list)


def validate(points: DataFrame, sigma: float, alpha: float, epsilon: float, delta: float) -> int:
    """Raises unless rows have unit length, ids are unique and parameters in range; returns the row count."""
    if not sigma > 0 or alpha < 0 or not epsilon > 0 or not 0 < delta < 1:
        raise ValueError("sigma > 0, alpha >= 0, epsilon > 0 and 0 < delta < 1 are needed")
    size = F.aggregate("x", F.lit(0.0), lambda s, z: s + z * z)
    n, ids, off, dims = points.agg(F.count(F.lit(1)), F.countDistinct("id"), F.sum((F.abs(size - 1) > 1e-6).cast("int")), F.countDistinct(F.size("x"))).first()
    if n < 3:
        raise ValueError("a release needs three rows at least")
    if ids != n or off or dims != 1:
        raise ValueError("rows need distinct ids, one dimension and unit length")
    return n


def labels_for(points: DataFrame, policy: str, epsilon: float | None = None, secret: str = "role IN ('target', 'dummy')") -> tuple[DataFrame, list[str]]:
    """The label column that later steps may read, by policy, and what the report must say of it."""
    if policy == "public":
        return points.select("id", "label"), ["labels are declared not sensitive"]
    if policy == "off":
        return points.select("id", F.lit(None).cast("int").alias("label")), []
    if policy == "masked":
        return points.select("id", F.when(F.expr(secret), None).otherwise(F.col("label")).alias("label")), ["labels of secret rows are not read"]
    if policy == "randomized":
        import math

        if epsilon is None:
            raise ValueError("randomized labels need their own epsilon")
        classes = sorted(r[0] for r in points.where("label IS NOT NULL").select("label").distinct().collect())
        keep = math.exp(epsilon) / (math.exp(epsilon) + len(classes) - 1)
        other = F.element_at(F.filter(F.array(*(F.lit(c) for c in classes)), lambda c: c != F.col("label")), (F.floor(F.rand() * (len(classes) - 1)) + 1).cast("int")) if len(classes) > 1 else F.col("label")
        drawn = points.select("id", F.when(F.col("label").isNull() | (F.rand() < keep), F.col("label")).otherwise(other).alias("label"))
        return cut(drawn, "labels"), [f"labels went through randomized response at epsilon {epsilon}"]
    raise ValueError(f"unknown label policy {policy}")


def published_labels(points: DataFrame, policy: str, epsilon: float | None = None, book: Book | None = None, subject: str = "client") -> tuple[DataFrame, list[str], float]:
    """``labels_for``, written; and the epsilon they cost, charged to ``book`` first."""
    cost = (epsilon or 0.0) if policy == "randomized" else 0.0
    if book is not None and cost:
        book.charge(subject, "randomized labels", cost, 0.0, 1.0)
    labels, said = labels_for(points, policy, epsilon)
    return (labels if getattr(labels, "at", None) else cut(labels, "labels")), said, cost


def noisy_first_step(
    points: DataFrame,
    m: int,
    sigma: float,
    alpha: float,
    epsilon: float,
    delta: float,
    sigma_q: float = 1.0,
    seed: int | str = 1,
    form: str = "uniform",
    calibration: str = "classic",
    domain: str = "sphere",
    t: int = 1,
    padding: str = "reserve",
    book: Book | None = None,
    subject: str = "client",
    test_noise: int | str | None = None,
) -> tuple[DataFrame, ReleaseReport]:
    """One contrast step on the dense exact graph with Gaussian noise, written once and read back.

    The sensitivity counts the start matrix of one row more (``padding``: see
    ``StartNorms``). ``book`` is charged before anything is published, or refuses.
    ``test_noise``: a seed for reproducible noise in tests, which hides nothing.
    """
    if t != 1:
        raise ValueError("the bound covers the first iteration only")
    n = validate(points, sigma, alpha, epsilon, delta)
    q = noise.start_matrix(points, m, sigma_q, seed)
    if padding == "reserve":
        norms = sensitivity.start_norms(q, seed, sigma_q, form == "spectral")
    elif padding == "tail" and form != "spectral":
        norms = sensitivity.tail_norms(n, m, sigma_q, delta / 10)
    else:
        raise ValueError(f"padding {padding} does not go with form {form}")
    gap = sensitivity.bound(n, alpha, sigma, norms, form, domain)
    tau = noise.calibrate(epsilon, delta - norms.beta, gap, calibration)
    step = contrast_step(q, DenseOp(sigma).over(points), LabelOp(points, sigma) if alpha else None, alpha)
    out = noise.add(step, tau) if test_noise is None else noise.add_test_noise(step, tau, test_noise, allow_test_noise=True)
    newcomer = "the start matrix's row of a newcomer is that of the next free id" if padding == "reserve" else "the start matrix's norm is bounded but for a tenth of delta"
    report = ReleaseReport(epsilon, delta, gap, tau, n, form, calibration, assumptions=["unit rows", "the row count is public", "the start matrix is independent of the data", newcomer, f"domain {domain}"])
    if test_noise is not None:
        report.assumptions.append("TEST NOISE: no privacy")
    if book is not None:
        book.charge(subject, "noisy first step", epsilon, delta, gap)
    out = cut(out.select("id", "v"), "release")
    return known_width(out, m), report


def resume(spark: SparkSession, path: str) -> DataFrame:
    """A release as another host reads it: from its files, and nothing else."""
    return spark.read.schema(EMBED).parquet(path)


def _plain(path: str) -> str:
    return path.replace("file://", "").replace("file:", "").rstrip("/")


def reads_only(df: DataFrame, *paths: str) -> bool:
    """Whether every file that a plan scans is or lies in one of ``paths``."""
    allowed = [_plain(p) for p in paths]
    return all(any(_plain(f) == p or _plain(f).startswith(p + "/") for p in allowed) for f in df.inputFiles())


class Barrier:
    """The privacy barrier as a property of plans: only the release, what was declared with it, and what was made from those may be read."""

    def __init__(self, *paths: str):
        self.paths = list(paths)

    def check(self, df: DataFrame) -> DataFrame:
        if not reads_only(df, *self.paths):
            raise PermissionError("a plan behind the privacy barrier reads other files than the release")
        return df

    def cut(self, df: DataFrame, name: str = "t") -> DataFrame:
        """Write a checked plan; what is written may be read from then on."""
        out = cut(self.check(df), name)
        self.paths.append(out.at)
        return out


def renormed(v: DataFrame, how: str = "rows") -> DataFrame:
    """Points ``(id, x)`` for the graph of a release: unit rows, one common scale, or as they are."""
    if how == "rows":
        return v.select("id", F.coalesce(unit(F.col("v")), F.col("v")).alias("x"))
    if how == "rms":
        rms = v.agg(F.sqrt(F.avg(F.aggregate("v", F.lit(0.0), lambda s, z: s + z * z)))).first()[0] or 1.0
        return v.select("id", F.transform("v", lambda z: z / F.lit(float(rms))).alias("x"))
    if how == "none":
        return v.select("id", F.col("v").alias("x"))
    raise ValueError(f"unknown renorm {how}")


def free_steps(released: DataFrame, labels: DataFrame, m: int, sigma: float, alpha: float, steps: int, rebuild: str = "once", renorm: str = "rows", op: Op | None = None, rescale: bool = True, barrier: Barrier | None = None) -> DataFrame:
    """Contrast steps on graphs built from the release alone. ``rebuild='each'`` builds a new graph before every step. With a ``barrier`` every plan is checked before it runs."""
    write = barrier.cut if barrier else cut
    v = known_width(released.select("id", "v"), m)
    rounds = [steps] if rebuild == "once" else [1] * steps
    if rebuild not in ("once", "each"):
        raise ValueError(f"unknown rebuild {rebuild}")
    for k in rounds:
        pts = renormed(v, renorm).join(labels, "id", "left").withColumn("role", F.lit(None).cast("string"))
        if barrier:
            barrier.check(pts)
        v = run(pts, m, sigma, alpha, k, op=op or DenseOp(sigma, single=True), start=v, rescale=rescale, write=write).v
    return v


def release_then_iterate(points: DataFrame, m: int, sigma: float, alpha: float, epsilon: float, delta: float, steps: int = 5, rebuild: str = "once", renorm: str = "rows", label_policy: str = "public", label_epsilon: float | None = None, op: Op | None = None, **release) -> tuple[DataFrame, ReleaseReport]:
    """Release once, rebuild the graph from the release, iterate without further cost.

    Labels that later steps may read are written before the barrier; behind it nothing but
    them and the release is read.
    """
    labels, said, cost = published_labels(points, label_policy, label_epsilon, release.get("book"), release.get("subject", "client"))
    out, report = noisy_first_step(points, m, sigma, alpha, epsilon, delta, **release)
    report.label_policy, report.epsilon = label_policy, report.epsilon + cost
    report.assumptions += said
    barrier = Barrier(out.at, labels.at)
    v = free_steps(resume(points.sparkSession, out.at), labels, m, sigma, 0.0 if label_policy == "off" else alpha, steps, rebuild, renorm, op, barrier=barrier)
    return v, report
