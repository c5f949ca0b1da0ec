"""The methods' arithmetic on arrays that fit one task: blocks of the distributed operators, and whole runs of small sets."""

from __future__ import annotations

import hashlib
import math

import numpy as np

#: Entries of a block of weights or distances that is held at once.
ENTRIES = 1 << 22
#: Rows and columns of a tile of weights.
TILE = 256, 512
#: Rows of a block that meets itself and, both ways at once, all later rows.
SIDE = 2048
#: Pairs from which products that are not released may take weights in single precision, about 6 digits.
SINGLE = 1e8
#: Candidates for each of k places from which single precision is taken for too coarse.
CROWD = 4
LAST = np.iinfo(np.int64).max


def _draws(seed: int | str, i: np.ndarray, m: int) -> np.ndarray:
    digest = "".join(hashlib.md5(f"{seed}:{a}:{j}".encode()).hexdigest()[:16] for a in i.tolist() for j in range(m))
    return (np.frombuffer(bytes.fromhex(digest), ">u4").reshape(len(i), m, 2).astype(np.float64) + 0.5) / 2.0**32


def normals(seed: int | str, i: np.ndarray, m: int) -> np.ndarray:
    """The portable standard normal draws for (seed, i, 0 .. m - 1), as ``functions.md5_normal`` makes them."""
    u = _draws(seed, i, m)
    return np.sqrt(-2.0 * np.log(u[..., 0])) * np.cos(2 * math.pi * u[..., 1])


def uniforms(seed: int | str, m: int) -> np.ndarray:
    """m portable uniform draws."""
    return _draws(seed, np.zeros(1, np.int64), m)[0, :, 0]


def square_gaps(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.maximum((x * x).sum(1)[:, None] + (y * y).sum(1)[None, :] - 2 * x @ y.T, 0.0)


def same(ids: np.ndarray, others: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of equal ids: rows and columns."""
    order = np.argsort(others, kind="stable")
    low, high = (np.searchsorted(others[order], ids, side) for side in ("left", "right"))
    n = high - low
    at = np.repeat(np.arange(len(ids)), n)
    return at, order[np.repeat(low, n) + np.arange(len(at)) - np.repeat(np.cumsum(n) - n, n)]


def _exponents(x: np.ndarray, y: np.ndarray, sigma: float) -> tuple[np.ndarray, np.ndarray]:
    """Two matrices whose product holds -distance^2 / sigma of all rows: one pass less over the pairs for each term."""
    nx, ny = -(x * x).sum(1) / sigma, -(y * y).sum(1) / sigma
    return np.c_[2 / sigma * x, nx, np.ones(len(x))], np.c_[y, np.ones(len(y)), ny]


def weights(ids: np.ndarray, x: np.ndarray, others: np.ndarray, y: np.ndarray, sigma: float) -> np.ndarray:
    """Kernel weights of rows with others; a row has none with itself."""
    a, b = _exponents(x, y, sigma)
    w = a @ b.T
    np.exp(np.minimum(w, 0.0, out=w), out=w)
    w[same(ids, others)] = 0.0
    return w


def product(ids: np.ndarray, x: np.ndarray, others: np.ndarray, y: np.ndarray, v: np.ndarray, sigma: float) -> tuple[np.ndarray, np.ndarray]:
    """Degrees of rows and their rows of W V, tile by tile: a tile stays in the cache."""
    out, _ = both_products(ids, x, others, y, None, np.c_[v, np.ones(len(v))], sigma)
    return out[:, -1].copy(), out[:, :-1].copy()


def _as_single(v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Columns in single precision, and what they were divided by: noise may be beyond its range."""
    most = np.abs(v).max(0, initial=0.0)
    scale = np.where(most > 0, most, 1.0)
    return (v / scale).astype(np.float32), scale


def both_products(ids: np.ndarray, x: np.ndarray, others: np.ndarray, y: np.ndarray, u: np.ndarray | None, v: np.ndarray, sigma: float, single: bool = False) -> tuple[np.ndarray, np.ndarray | None]:
    """W V and, if ``u`` is given, W' U of the weights W of rows with others: each is computed once for both ways.

    ``single``: weights in single precision, of rows moved to their middle; sums of tiles are added up in double precision.
    """
    out, back = np.zeros((len(ids), v.shape[1])), None if u is None else np.zeros((len(others), u.shape[1]))
    if single:
        middle = y.mean(0) if len(y) else 0.0
        x, y = x - middle, y - middle
        (v, by), (u, of) = _as_single(v), (None, None) if u is None else _as_single(u)
    a, b = _exponents(x, y, sigma)
    if single:
        a, b = a.astype(np.float32), b.astype(np.float32)
    at, col = same(ids, others)
    order = np.argsort(col, kind="stable")
    at, col = at[order], col[order]
    room = np.empty(TILE[0] * TILE[1], a.dtype)
    for j in range(0, len(others), TILE[1]):
        part, own = np.ascontiguousarray(b[j : j + TILE[1]].T), slice(*np.searchsorted(col, (j, j + TILE[1])))
        for i in range(0, len(ids), TILE[0]):
            rows = a[i : i + TILE[0]]
            w = np.matmul(rows, part, out=room[: len(rows) * part.shape[1]].reshape(len(rows), -1))
            np.exp(w if single else np.minimum(w, 0.0, out=w), out=w)
            here = (at[own] >= i) & (at[own] < i + TILE[0])
            w[at[own][here] - i, col[own][here] - j] = 0.0
            out[i : i + TILE[0]] += w @ v[j : j + TILE[1]]
            if back is not None:
                back[j : j + TILE[1]] += w.T @ u[i : i + TILE[0]]
    if single:
        out *= by
        if back is not None:
            back *= of
    return out, back


def unit(x: np.ndarray) -> np.ndarray:
    """Rows at length 1; zero rows stay."""
    n = np.linalg.norm(x, axis=1, keepdims=True)
    return x / np.where(n > 0, n, 1.0)


class Filter:
    """Squared distances of rows, in single precision: pairs above a limit are left out for certain, the others are to be measured.

    Rows are moved to the middle of ``y`` and scaled to length 1 at most, where a rounded
    sum of d + 1 products errs by less than ``err``.
    """

    def __init__(self, x: np.ndarray, y: np.ndarray):
        middle = y.mean(0) if len(y) else 0.0
        x, y = x - middle, y - middle
        longest = max((float(np.sqrt(np.einsum("ij,ij->i", z, z).max())) for z in (x, y) if len(z)), default=0.0)
        self.scale = longest if longest > 0 else 1.0
        x /= self.scale
        y /= self.scale
        self.own, ny = np.einsum("ij,ij->i", x, x), np.einsum("ij,ij->i", y, y)
        self.x, self.y = np.c_[x, np.ones(len(x))].astype(np.float32), np.c_[-2 * y, ny].astype(np.float32)
        self.long = x, y, ny
        self.err = 3 * 6e-8 * (y.shape[1] + 8)

    def gaps(self, q: slice, s: slice) -> np.ndarray:
        """Scaled squared distances less the squared length of the row of ``x``."""
        return self.x[q] @ self.y[s].T

    def below(self, gaps: np.ndarray, limit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return np.divmod(np.flatnonzero(gaps <= limit.astype(np.float32)[:, None]), max(1, gaps.shape[1]))

    def under(self, q: slice, s: slice, limit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """``below`` of ``gaps``, tile by tile: a tile stays in the cache."""
        x, y, limit, found = self.x[q], self.y[s], limit.astype(np.float32)[:, None], []
        room, less = np.empty(TILE[0] * TILE[1], np.float32), np.empty(TILE[0] * TILE[1], bool)
        for i in range(0, len(x), TILE[0]):
            rows, most = x[i : i + TILE[0]], limit[i : i + TILE[0]]
            for j in range(0, len(y), TILE[1]):
                cols = y[j : j + TILE[1]].T
                shape = len(rows), cols.shape[1]
                g = np.matmul(rows, cols, out=room[: shape[0] * shape[1]].reshape(shape))
                at, col = np.divmod(np.flatnonzero(np.less_equal(g, most, out=less[: g.size].reshape(shape))), shape[1])
                found.append((at + i, col + j))
        return tuple(np.concatenate(z) for z in zip((np.empty(0, np.int64),) * 2, *found, strict=True))

    def closer(self, q: slice, s: slice, square: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """``below`` in double precision, for the ``k`` least of a row without limit: for rows that lie closer than single precision tells apart."""
        x, y, ny = self.long
        gaps, err = x[q] @ (-2 * y[s].T) + ny[s], 3 * 2.3e-16 * (y.shape[1] + 8)
        limit = (square + 1e-12) / self.scale**2 - self.own[q] + 2 * err
        new = ~np.isfinite(limit)
        if new.any() and gaps.shape[1] > k:
            limit[new] = np.partition(gaps[new], k - 1, axis=1)[:, k - 1] + 2 * err + 1e-12 / self.scale**2
        return np.nonzero(gaps <= limit[:, None])

    def limit(self, square: np.ndarray, q: slice) -> np.ndarray:
        """What ``gaps`` have at most where the squared distance is ``square`` at most."""
        return square / self.scale**2 - self.own[q] + 2 * self.err


def measured(x: np.ndarray, y: np.ndarray, at: np.ndarray, col: np.ndarray) -> np.ndarray:
    """Squared distances of chosen pairs, each from its differences: equal rows have equal ones."""
    out = np.empty(len(at))
    for i in range(0, len(at), 1 << 16):
        gap = x[at[i : i + (1 << 16)]] - y[col[i : i + (1 << 16)]]
        out[i : i + (1 << 16)] = (gap * gap).sum(1)
    return out


def nearest(qid: np.ndarray, x: np.ndarray, rid: np.ndarray, y: np.ndarray, k: int, metric: str = "l2", skip_self: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Ids and distances (to 12 decimals) of the k nearest rows of each query, ties by id; missing ones are ``LAST`` and infinite."""
    if metric == "cosine":
        x, y = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300), y / np.maximum(np.linalg.norm(y, axis=1, keepdims=True), 1e-300)
    best, found = np.full((len(qid), k), np.inf), np.full((len(qid), k), LAST)
    quick = Filter(x, y) if metric == "l2" and len(qid) and len(rid) else None
    if quick is not None and not np.isfinite(quick.scale):
        quick = None
    for q in range(0, len(qid), 1024):
        rows = slice(q, q + 1024)
        xs, own = x[rows], qid[rows]
        for s in range(0, len(rid), 4096):
            ids, ys = rid[s : s + 4096], y[s : s + 4096]
            d, i = best[rows], found[rows]
            if quick is not None:
                kk = k + skip_self
                limit = quick.limit(d[:, -1] + 1e-12, rows)
                new = ~np.isfinite(limit)
                if new.any() and len(ids) > kk:
                    g = quick.gaps(rows, slice(s, s + 4096))
                    limit[new] = np.partition(g[new], kk - 1, axis=1)[:, kk - 1] + 2 * quick.err + 1e-12 / quick.scale**2
                at, col = quick.under(rows, slice(s, s + 4096), limit)
                if len(at) > CROWD * kk * len(xs):
                    at, col = quick.closer(rows, slice(s, s + 4096), d[:, -1], kk)
                gap = np.round(measured(xs, ys, at, col), 12) + 0.0
                keep = gap <= d[at, -1]
                if skip_self:
                    keep &= own[at] != ids[col]
                at, col, gap = at[keep], col[keep], gap[keep]
            else:
                every = np.round(1 - xs @ ys.T if metric == "cosine" else square_gaps(xs, ys), 12) + 0.0
                if skip_self:
                    every[own[:, None] == ids[None, :]] = np.inf
                kk = min(k, len(ids))
                limit = np.minimum(np.partition(every, kk - 1, axis=1)[:, kk - 1] if len(ids) > kk else np.inf, d[:, -1])
                at, col = np.nonzero((every <= limit[:, None]) & (every < np.inf))
                gap = every[at, col]
            if not len(at):
                continue
            who = np.r_[at, np.repeat(np.arange(len(own)), k)]
            dist, match = np.r_[gap, d.ravel()], np.r_[ids[col], i.ravel()]
            order = np.lexsort((match, dist, who))
            place = np.arange(len(who)) - np.searchsorted(who[order], who[order])
            top = order[place < k]
            best[rows], found[rows] = dist[top].reshape(-1, k), match[top].reshape(-1, k)
    return found, best


def label_product(v: np.ndarray, label: np.ndarray, sigma_y: float, kernel: str = "gaussian_code") -> np.ndarray:
    """L_Y V from class sums; a missing (nan) label has no edges."""
    out, known = np.zeros_like(v), ~np.isnan(label)
    codes, of = np.unique(label[known], return_inverse=True)
    if not len(codes):
        return out
    k = np.exp(-((codes[:, None] - codes[None]) ** 2) / sigma_y) if kernel == "gaussian_code" else np.eye(len(codes))
    sums = np.zeros((len(codes), v.shape[1]))
    np.add.at(sums, of, v[known])
    out[known] = (k @ np.bincount(of, minlength=len(codes)))[of, None] * v[known] - (k @ sums)[of]
    return out


class Graph:
    """The feature graph of one set of rows, held if it is small, else computed again in each product; ``single``: from ``SINGLE`` pairs on in single precision."""

    def __init__(self, x: np.ndarray, sigma: float, single: bool = False):
        self.x, self.sigma, self.ids, self.single, self.deg = x, sigma, np.arange(len(x)), single and len(x) ** 2 >= SINGLE, None
        self.w = weights(self.ids, x, self.ids, x, sigma) if len(x) ** 2 <= ENTRIES else None

    def apply(self, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if self.w is not None:
            return self.w.sum(1), self.w @ v
        n, u = len(self.x), v if self.deg is not None else np.c_[v, np.ones(len(v))]
        out = np.zeros_like(u)
        for i in range(0, n, SIDE):
            own, rest = slice(i, i + SIDE), slice(i + SIDE, n)
            out[own] += both_products(self.ids[own], self.x[own], self.ids[own], self.x[own], None, u[own], self.sigma, self.single)[0]
            here, there = both_products(self.ids[own], self.x[own], self.ids[rest], self.x[rest], u[own], u[rest], self.sigma, self.single)
            out[own] += here
            out[rest] += there
        if self.deg is None:
            self.deg, out = out[:, -1].copy(), out[:, :-1].copy()
        return self.deg, out


def step(v: np.ndarray, graph: Graph, label: np.ndarray, alpha: float, sigma_y: float, log: list | None = None) -> np.ndarray:
    """One contrast step; ``log`` gets the objective of ``v``."""
    deg, wv = graph.apply(v)
    lx = deg[:, None] * v - wv
    ly = label_product(v, label, sigma_y) if alpha else np.zeros_like(v)
    if log is not None:
        log.append(float((v * lx).sum() - alpha * (v * ly).sum()))
    half = np.divide(0.5, deg, out=np.zeros_like(deg), where=deg != 0)
    return v + half[:, None] * (alpha * ly - lx)


def run(x: np.ndarray, label: np.ndarray, start: np.ndarray, sigma: float, alpha: float, steps: int, rescale: bool = True, log: list | None = None) -> list[np.ndarray]:
    """Every iterate, the start included; with ``log`` also the objective of each, and the logarithm of all scales taken off by then."""
    graph, out, scale, objective = Graph(x, sigma, log is None), [start], 0.0, []
    for t in range(steps + (log is not None)):
        new = step(out[-1], graph, label, alpha, sigma, objective if log is not None else None)
        if log is not None:
            log.append((objective[-1], scale))
        if t == steps:
            break
        if rescale:
            rms = math.sqrt(float((new * new).mean())) or 1.0
            new, scale = new / rms, scale + math.log(rms)
        out.append(new)
    return out


def free_steps(released: np.ndarray, label: np.ndarray, sigma: float, alpha: float, steps: int) -> np.ndarray:
    """Steps on the graph of the released rows alone."""
    return run(unit(released), label, released, sigma, alpha, steps)[-1]


def top_directions(g: np.ndarray, m: int) -> np.ndarray:
    """The m leading eigenvectors, each with its largest entry positive."""
    values, vectors = np.linalg.eigh((g + g.T) / 2)
    v = vectors[:, np.argsort(-values)[:m]]
    return v * np.where(v[np.abs(v).argmax(0), np.arange(v.shape[1])] < 0, -1.0, 1.0)


def motion(cross: np.ndarray, spread: float, scale: bool = False, reflect: bool = False) -> tuple[np.ndarray, float]:
    """Rotation and scale of least squared error from the cross-covariance of source and target; a reflection only if asked for."""
    u, d, vt = np.linalg.svd(cross)
    sign = np.ones(len(d))
    if not reflect and np.linalg.det(u @ vt) < 0:
        sign[-1] = -1
    return u @ np.diag(sign) @ vt, float((d * sign).sum() / spread) if scale and spread > 0 else 1.0


def align(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rotation and shift of rows ``a`` onto rows ``b``."""
    ma, mb = a.mean(0), b.mean(0)
    r, _ = motion((a - ma).T @ (b - mb) / len(a), 0.0)
    return r, mb - ma @ r


def row_bandwidths(gaps: np.ndarray, perplexity: float) -> np.ndarray:
    """Conditional affinities of each row (own column masked as inf) at the given perplexity, by bisection of all rows at once."""
    n, k = gaps.shape
    goal = math.log(max(1.001, min(perplexity, k - 1)))
    low, high, beta = np.zeros(n), np.full(n, np.inf), np.ones(n)
    shifted = gaps - gaps.min(1, keepdims=True)
    for _ in range(60):
        p = np.exp(-shifted * beta[:, None])
        p[~np.isfinite(gaps)] = 0
        total = p.sum(1)
        entropy = np.log(total) + beta * (p * np.where(np.isfinite(shifted), shifted, 0)).sum(1) / total
        wide = entropy > goal
        low, high = np.where(wide, beta, low), np.where(wide, high, beta)
        beta = np.where(np.isinf(high), beta * 2, (low + high) / 2)
    return p / p.sum(1, keepdims=True)


class Descent:
    """Gradient descent with momentum, gains and early exaggeration, as t-SNE does it."""

    def __init__(self, y: np.ndarray, rate: float, exaggerate: float):
        self.y, self.rate, self.factor = y, rate, exaggerate
        self.speed, self.gain, self.t = np.zeros_like(y), np.ones_like(y), 0

    @property
    def exaggerate(self) -> float:
        return self.factor if self.t < 100 else 1.0

    def move(self, force: np.ndarray) -> None:
        self.gain = np.maximum(np.where(np.sign(force) != np.sign(self.speed), self.gain + 0.2, self.gain * 0.8), 0.01)
        self.speed = (0.5 if self.t < 100 else 0.8) * self.speed - self.rate * self.gain * force
        self.y = self.y + self.speed
        self.y -= self.y.mean(0)
        self.t += 1


#: Widest stretch of places that lie on a grid of ``repulsion``.
WIDE = 64.0


def too_wide(y: np.ndarray) -> bool:
    """Whether places are too far apart for a grid, or not in a plane."""
    return y.shape[1] != 2 or not float((y.max(0) - y.min(0)).max()) <= WIDE


def repulsion(y: np.ndarray, nodes: int = 10, spacing: float = 1 / 20) -> tuple[np.ndarray, float]:
    """For places in the plane, the sum of q^2 (y_i - y_j) of each row over all others, and the sum of q over all pairs, q = 1 / (1 + distance^2).

    Every pair counts: q is smooth, so each place is written as a polynomial through ``nodes`` x
    ``nodes`` points of a grid around it, and the sums between all grid points are two
    convolutions. Sums are right to about 8 digits.
    """
    low, n = y.min(0), len(y)
    side = int(float((y - low).max()) / spacing) + nodes + 1
    at = np.arange(nodes)
    parts = [slice(i, i + 65536) for i in range(0, n, 65536)]

    def spread(rows: slice) -> tuple[np.ndarray, np.ndarray]:
        base = np.floor((y[rows] - low) / spacing)
        t = ((y[rows] - low) / spacing - base + nodes // 2 - 1)[:, :, None]
        w = np.ones((*t.shape[:2], nodes))
        for k in range(nodes):
            w[:, :, at != k] *= (t - k) / (at[at != k] - k)
        place = base.astype(np.int64)[:, :, None] + at
        return (place[:, 0, :, None] * side + place[:, 1, None, :]).reshape(len(t), -1), (w[:, 0, :, None] * w[:, 1, None, :]).reshape(len(t), -1)

    charge = np.zeros((3, side * side))
    for rows in parts:
        place, w = spread(rows)
        for c, of in enumerate((None, y[rows, :1], y[rows, 1:])):
            charge[c] += np.bincount(place.ravel(), (w if of is None else w * of).ravel(), side * side)
    far = spacing * np.minimum(np.arange(2 * side), 2 * side - np.arange(2 * side))
    q = 1 / (1 + far[:, None] ** 2 + far[None] ** 2)
    one, two = np.fft.rfft2(q), np.fft.rfft2(q * q)
    field = np.empty((4, side * side))
    for c in range(3):
        f = np.fft.rfft2(charge[c].reshape(side, side), (2 * side, 2 * side))
        field[c] = np.fft.irfft2(f * two, (2 * side, 2 * side))[:side, :side].ravel()
        if not c:
            field[3] = np.fft.irfft2(f * one, (2 * side, 2 * side))[:side, :side].ravel()
    out, total = np.empty_like(y), 0.0
    for rows in parts:
        place, w = spread(rows)
        s = [(w * field[c][place]).sum(1) for c in range(4)]
        out[rows] = s[0][:, None] * y[rows] - np.c_[s[1], s[2]]
        total += float(s[3].sum())
    return out, total - n


def tsne(x: np.ndarray, start: np.ndarray, perplexity: float, iterations: int, rate: float, exaggerate: float, log: list | None = None) -> np.ndarray:
    """t-SNE with exact affinities of all pairs."""
    n = len(x)
    g = square_gaps(x, x)
    np.fill_diagonal(g, np.inf)
    cond = row_bandwidths(g, perplexity)
    joint = np.maximum((cond + cond.T) / (2 * n), 1e-12)
    d = Descent(start, rate, exaggerate)
    for _ in range(iterations):
        q = 1 / (1 + square_gaps(d.y, d.y))
        np.fill_diagonal(q, 0)
        share = np.maximum(q / q.sum(), 1e-12)
        pull = (joint * d.exaggerate - share) * q
        if log is not None:
            log.append(float((joint * np.log(joint / share)).sum()))
        d.move(4 * (pull.sum(1)[:, None] * d.y - pull @ d.y))
    return d.y


def site_forces(w: np.ndarray, now: np.ndarray, clip: float) -> np.ndarray:
    """Sum over rows of their clipped forces on the anchors, given the rows' affinities to them."""
    total = np.zeros_like(now)
    for i in range(0, len(w), 256):
        p = w[i : i + 256]
        spot = p @ now  # a row's place among the anchors
        q = 1 / (1 + square_gaps(spot, now))
        q /= q.sum(1, keepdims=True)
        f = (p - q)[:, :, None] * (now[None] - spot[:, None])
        f *= np.minimum(1.0, clip / np.maximum(np.sqrt((f * f).sum((1, 2))), 1e-300))[:, None, None]
        total += f.sum(0)
    return total


def sne_round_cost(epsilon: float, delta: float, rounds: int) -> tuple[float, float]:
    """Zero-concentrated privacy of all rounds and of one, for half of epsilon: eps = rho + 2 sqrt(rho ln(1 / delta))."""
    part, log_d = epsilon / 2, math.log(2 / delta)
    rho = (math.sqrt(log_d + part) - math.sqrt(log_d)) ** 2
    return rho, rho / rounds


def sne_rounds(anchors: np.ndarray, forces, sizes: dict[int, int], m: int, each: float, clip: float, iterations: int, rate: float, perplexity: float, seed: int, rng: np.random.Generator | None) -> np.ndarray:
    """Anchors placed together by several sites. ``forces(places)``: by site, the sum of its rows' forces; noise from ``rng``."""
    return sne_rounds_many(anchors, lambda y: [forces(y[0])], sizes, m, [each], clip, iterations, rate, perplexity, [seed], rng)[0]


def sne_rounds_many(anchors: np.ndarray, forces, sizes: dict[int, int], m: int, each: list[float], clip: float, iterations: int, rate: float, perplexity: float, seeds: list[int], rng: np.random.Generator | None) -> list[np.ndarray]:
    """``sne_rounds`` of several runs on the same anchors, round by round: ``forces`` takes the places of each and gives those of each."""
    ys = [np.random.default_rng(seed).normal(0, 1e-2, (len(anchors), m)) for seed in seeds]
    g = square_gaps(anchors, anchors)
    np.fill_diagonal(g, np.inf)
    cond = row_bandwidths(g, perplexity)
    joint = (cond + cond.T) / (2 * len(anchors))
    for _ in range(iterations):
        for r, parts in enumerate(forces(ys)):
            y, push = ys[r], np.zeros_like(ys[r])
            for s, n in sorted(sizes.items()):
                f = parts.get(s, np.zeros_like(y))
                if rng is not None:
                    f = f + rng.normal(0, clip / math.sqrt(2 * each[r]), y.shape)
                push += f / n / len(sizes)
            q = 1 / (1 + square_gaps(y, y))
            np.fill_diagonal(q, 0)
            pull = (joint - q / q.sum()) * q
            ys[r] = y - rate * (4 * (pull.sum(1)[:, None] * y - pull @ y) + push)
    return ys


def diameter(y: np.ndarray) -> float:
    """A bound of the distance of any two rows."""
    return max(1e-12, float(np.sqrt(square_gaps(y, y).max())) if len(y) < 3000 else 2 * float(np.linalg.norm(y, axis=1).max()))
