"""Numeric kernels over one window: entities are rows of x (n, M), correlations are (n, n).  Pure numpy, no Spark."""

from __future__ import annotations

from typing import NamedTuple

import numpy as np

from .special import digamma1, inv_digamma1, log_beta

MODES = ("abs", "positive", "negative", "signed")


def pearson(x: np.ndarray, other: np.ndarray | None = None) -> np.ndarray:
    """Signed correlations of the rows of x with those of other (default x itself); a constant row has 0 with all."""

    def unit(a: np.ndarray) -> np.ndarray:
        c = a - a.mean(1, keepdims=True)
        size = np.sqrt((c * c).sum(1, keepdims=True))
        return np.divide(c, size, out=np.zeros_like(c), where=size > 1e-12)

    u = unit(x.astype(float))
    p = np.clip(u @ (u if other is None else unit(other.astype(float))).T, -1, 1)
    if other is None:
        np.fill_diagonal(p, 1.0)
    return p


def in_mode(p: np.ndarray, mode: str = "abs") -> np.ndarray:
    """Entries by sign mode; the diagonal of a square self-correlation keeps its 1 as all modes map 1 to 1 or are reset by the caller."""
    if mode == "abs":
        return np.abs(p)
    if mode == "positive":
        return np.maximum(p, 0)
    if mode == "negative":
        return np.maximum(-p, 0)
    if mode == "signed":
        return p
    raise ValueError(f"mode must be one of {MODES}")


def correlations(x: np.ndarray, mode: str = "abs") -> np.ndarray:
    p = in_mode(pearson(x), mode)
    np.fill_diagonal(p, 1.0)
    return p


def lanczos(p: np.ndarray, start: np.ndarray | None = None, steps: int = 40, tol: float = 1e-10) -> tuple[float, np.ndarray, int]:
    """(largest eigenvalue, its unit vector with a non-negative sum, steps done); full reorthogonalisation."""
    n = len(p)
    q = np.ones(n) if start is None or not np.any(start) else np.abs(start)
    basis = [q / np.linalg.norm(q)]
    alpha, beta = [], []
    for k in range(min(steps, n)):
        v = p @ basis[-1]
        alpha.append(float(basis[-1] @ v))
        b = np.array(basis)
        v = v - b.T @ (b @ v)
        v = v - b.T @ (b @ v)
        size = float(np.linalg.norm(v))
        values, vectors = np.linalg.eigh(np.diag(alpha) + np.diag(beta, 1) + np.diag(beta, -1))
        if size * abs(vectors[-1, -1]) < tol * max(abs(values[-1]), 1e-300) or size < 1e-13:
            break
        beta.append(size)
        basis.append(v / size)
    q = np.array(basis[: len(alpha)]).T @ vectors[:, -1]
    q = q if q.sum() >= 0 else -q
    return float(values[-1]), q / np.linalg.norm(q), len(alpha)


def principal(p: np.ndarray, exact: int = 0, start: np.ndarray | None = None) -> tuple[float, np.ndarray, int]:
    """Largest eigenvalue and vector: exact solver up to `exact` rows, else Lanczos."""
    if not len(p):
        return 0.0, np.zeros(0), 0
    if len(p) <= exact:
        values, vectors = np.linalg.eigh(p)
        q = vectors[:, -1]
        return float(values[-1]), q if q.sum() >= 0 else -q, 0
    return lanczos(p, start)


def loadings(p: np.ndarray, q: np.ndarray, lam: float) -> np.ndarray:
    """Correlation of each entity with the principal component."""
    return np.minimum(np.abs(p @ q) / np.sqrt(max(lam, 1e-300)), 1.0)


def norms(x: np.ndarray, p: float) -> np.ndarray:
    a = np.abs(x)
    return a.max(1, initial=0.0) if np.isinf(p) else (a**p).sum(1) ** (1 / p)


def whole_weights(norm: np.ndarray) -> np.ndarray:
    """Magnitudes in millionths, so that sums are exact whatever their order."""
    return np.floor(norm * 1e6 + 0.5).astype(np.int64)


def systematic(weight: np.ndarray, m: int, u: float = 0.5) -> np.ndarray:
    """How often each entity is drawn: m evenly spaced points on the cumulated weights, in the given order."""
    total = int(weight.sum())
    if total <= 0:
        return np.zeros(len(weight), np.int64)
    c = np.cumsum(weight)
    up = np.floor(m * c / total + u).astype(np.int64)
    return np.diff(np.r_[np.int64(np.floor(u)), up])


class Sampled(NamedTuple):
    score: float
    lam: float
    drawn: np.ndarray  # rows drawn
    mult: np.ndarray
    loading: np.ndarray  # of all rows
    steps: int


def sampled_score(x: np.ndarray, mult: np.ndarray, mode: str = "abs", whole: bool = True, exact: int = 0) -> Sampled:
    """Principal score of the sampled columns, repeats counted, from the distinct ones: D^1/2 P D^1/2 has the eigenvalues of
    the matrix with repeats.  The loadings of all rows follow from their correlations with the sample."""
    from .folded import Folded

    return Folded(x.astype(float), mode).sampled(mult, whole, exact)


# ---- beta block model ------------------------------------------------------------------------------------------------


class BlockConfig(NamedTuple):
    k: int = 2
    mean_floor: float = 0.75
    background_top: float = 0.5
    clamp: float = 1e-3
    max_iter: int = 30
    unimodal: bool = False
    schedule: str = "synchronous"
    pairs: int | None = None  # if set, so many pairs of Columns drawn at random stand for the background; no query sets it


def drawn_pairs(n: int, pairs: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Ends of so many pairs of n entities, drawn at random."""
    rng = np.random.default_rng(seed)
    i = rng.integers(0, n, pairs)
    return i, (i + rng.integers(1, n, pairs)) % n


class Totals(NamedTuple):
    """Of all pairs: their number, sums of the clamped correlations and of ln and ln(1 - .), and the share at a floor or over."""

    pairs: float
    s: float
    s1: float
    s2: float
    near: float


class Columns:
    """Correlations of one window, made column by column when they are asked for: the block model reads those of grouped
    entities alone, so its cost is in their number times n and not in n squared.

    u: unit rows; or p: the whole matrix.  Unread parts of the arrays take no memory."""

    def __init__(self, u: np.ndarray | None = None, p: np.ndarray | None = None, mode: str = "abs", clamp: float = 1e-3) -> None:
        self.u, self.whole, self.mode, self.clamp = u, p, mode, clamp
        self.n = len(u if p is None else p)
        self.p, self.l1, self.l2 = (np.empty((self.n, self.n), order="F") for _ in range(3))
        self.have = np.zeros(self.n, bool)

    def need(self, at: np.ndarray) -> None:
        new = at[~self.have[at]]
        if len(new):
            c = self.whole[:, new] if self.whole is not None else in_mode(np.clip(self.u @ self.u[new].T, -1, 1), self.mode)
            w = np.clip(c, self.clamp, 1 - self.clamp)
            self.p[:, new], self.l1[:, new], self.l2[:, new] = c, np.log(w), np.log1p(-w)
            self.p[new, new], self.l1[new, new], self.l2[new, new] = 1.0, 0.0, 0.0
            self.have[new] = True

    def inner(self, at: np.ndarray) -> np.ndarray:
        self.need(at)
        return self.p[np.ix_(at, at)]

    def totals(self, floor: float, pairs: int | None = None, seed: int = 7) -> Totals:
        """Of all pairs, or as `pairs` of them drawn at random have it where there are more than twice as many."""
        n, every = self.n, self.n * (self.n - 1) // 2
        if pairs is not None and every > 2 * pairs:
            i, j = drawn_pairs(n, pairs, seed)
        else:
            i, j = np.triu_indices(n, 1)
        parts = []
        for lo in range(0, len(i), 1 << 16):
            a, b = i[lo : lo + (1 << 16)], j[lo : lo + (1 << 16)]
            p = self.whole[a, b] if self.whole is not None else in_mode(np.clip(np.einsum("ij,ij->i", self.u[a], self.u[b]), -1, 1), self.mode)
            w = np.clip(p, self.clamp, 1 - self.clamp)
            parts.append((w.sum(), np.log(w).sum(), np.log1p(-w).sum(), (p >= floor).sum()))
        s, s1, s2, near = np.sum(parts, 0) / max(len(i), 1)
        return Totals(every, s * every, s1 * every, s2 * every, near)

    def inside(self, at: np.ndarray) -> float:
        return float((self.inner(at).sum() - len(at)) / 2)

    def moved(self, came: np.ndarray, went: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        self.need(came)
        return tuple(x[:, came].sum(1) - x[:, went].sum(1) for x in (self.l1, self.l2))

    def gain_of_one(self, i: int, z: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        self.need(np.flatnonzero(z))
        return gains(self.l1, self.l2, z, a, b, np.array([i]))[0]


class Block(NamedTuple):
    z: np.ndarray  # 0 is background
    a: np.ndarray  # of groups 0..k
    b: np.ndarray
    rounds: int
    touched: int  # pair entries read by label updates
    history: list[float]  # log-likelihood after each accepted round
    near: float  # share of all pairs that are at the mean floor or over


def project(a: float, b: float, least: float, most: float, unimodal: bool) -> tuple[float, float]:
    """Nearest allowed shape: a + b >= 1, mean within [least, most], and a, b >= 1 if it must be unimodal."""
    t = max(a + b, 1.0)
    mean = min(max(a / (a + b), least), most)
    if unimodal:
        t = max(t, 1 / max(min(mean, 1 - mean), 1e-6))
    return t * mean, t * (1 - mean)


def fit_beta(mean_ln: float, mean_ln1m: float, a: float, b: float, least: float, most: float, unimodal: bool = False, rounds: int = 30) -> tuple[float, float]:
    """Maximum-likelihood shape from the mean logs, alternating on a and b, kept within the allowed shapes."""
    for _ in range(rounds):
        s = digamma1(a + b)
        na, nb = inv_digamma1(s + mean_ln), inv_digamma1(s + mean_ln1m)
        na, nb = project(min(max(na, 1e-3), 1e4), min(max(nb, 1e-3), 1e4), least, most, unimodal)
        done = abs(na - a) + abs(nb - b) < 1e-7 * (a + b)
        a, b = na, nb
        if done:
            break
    return a, b


def from_mean(mean: float, least: float, most: float, spread: float = 10.0) -> tuple[float, float]:
    mean = min(max(mean, least), most)
    return spread * mean, spread * (1 - mean)


def farthest_first(p: np.ndarray, members: np.ndarray, k: int) -> np.ndarray:
    """Labels 1..k of the members: the first seed has the greatest correlation sum, each next one is least correlated with
    the seeds so far, and all join their closest seed.  Seeds that are as good as copies of a seed are not taken."""
    if not len(members):
        return np.zeros(0, np.int64)
    own = p[np.ix_(members, members)]
    seeds = [int(own.sum(1).argmax())]
    while len(seeds) < min(k, len(members)):
        far = own[:, seeds].max(1)
        nxt = int(far.argmin())
        if far[nxt] >= 0.7:
            break
        seeds.append(nxt)
    return own[:, seeds].argmax(1) + 1


def neighbourhoods(p: np.ndarray, cut: float, k: int) -> np.ndarray:
    """Labels from the k densest disjoint neighbourhoods of entities correlated at least `cut`; 0 elsewhere."""
    z = np.zeros(len(p), np.int64)
    near = p >= cut
    np.fill_diagonal(near, False)
    free = np.ones(len(p), bool)
    count = near.sum(1)
    for g in range(1, k + 1):
        degree = np.where(free, count, -1)
        top = int(degree.argmax()) if len(degree) else 0
        if not len(degree) or degree[top] < 1:
            break
        own = near[top] & free
        own[top] = True
        z[own] = g
        free &= ~own
        count = count - near[:, own].sum(1)
    return z


def block_likelihood(m: np.ndarray, s1: np.ndarray, s2: np.ndarray, a: np.ndarray, b: np.ndarray) -> float:
    return float(((a - 1) * s1 + (b - 1) * s2 - m * log_beta(a, b)).sum())


def gains(l1: np.ndarray, l2: np.ndarray, z: np.ndarray, a: np.ndarray, b: np.ndarray, rows: np.ndarray | None = None) -> np.ndarray:
    """(rows, k + 1): change of the log-likelihood if the entity alone were in that group and not in the background.
    Only columns of grouped entities are read."""
    rows = np.arange(len(z)) if rows is None else rows
    out = np.zeros((len(rows), len(a)))
    base = log_beta(a, b)
    for g in range(1, len(a)):
        at = np.flatnonzero(z == g)
        if len(at):
            self_ = z[rows] == g
            out[:, g] = (a[g] - a[0]) * l1[np.ix_(rows, at)].sum(1) + (b[g] - b[0]) * l2[np.ix_(rows, at)].sum(1) + (len(at) - self_) * (base[0] - base[g])
    return out


def block_model(p, z: np.ndarray, cfg: BlockConfig = BlockConfig()) -> Block:  # noqa: ANN001, B008
    """Groups of the correlations p (a matrix, Columns, or folded.Folded) from first labels z (0 background, 1..k): alternate shape fits and label updates
    until no label changes; a round that would lower the likelihood keeps only its better half of moves, or ends.

    The background is all pairs (totals) less the groups' pairs."""
    c = Columns(p=p, clamp=cfg.clamp) if isinstance(p, np.ndarray) else p
    n, k = c.n, cfg.k
    if n < 2:
        return Block(np.zeros(n, np.int64), np.ones(k + 1), np.ones(k + 1), 0, 0, [], 0.0)
    whole, opened = c.opened(z, k, cfg.mean_floor) if cfg.pairs is None and hasattr(c, "opened") else (c.totals(cfg.mean_floor, cfg.pairs), None)
    total = (whole.pairs, whole.s1, whole.s2)
    a, b = np.ones(k + 1), np.ones(k + 1)
    limits = [(0.0, cfg.background_top)] + [(cfg.mean_floor, 1.0 - 1e-6)] * k
    z = z.copy()
    inside, pairs = 0.0, 0
    for g in range(1, k + 1):
        at = np.flatnonzero(z == g)
        m = len(at) * (len(at) - 1) / 2
        s = c.inside(at)
        inside, pairs = inside + s, pairs + m
        a[g], b[g] = from_mean(s / m if m else cfg.mean_floor, *limits[g])
    a[0], b[0] = from_mean((whole.s - inside) / max(whole.pairs - pairs, 1), *limits[0])

    def sums(old: np.ndarray, new: np.ndarray, t: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """Each entity's sums of ln and ln(1 - .) with the members of each group, from those of the old labels: only columns
        of entities that came or went are read."""
        nonlocal touched
        out = t[0].copy(), t[1].copy()
        for g in range(1, k + 1):
            came, went = np.flatnonzero((new == g) & (old != g)), np.flatnonzero((old == g) & (new != g))
            touched += n * (len(came) + len(went))
            if len(came) or len(went):
                for o, x in zip(out, c.moved(came, went)):
                    o[:, g] += x
        return out

    def fitted(z: np.ndarray, t: tuple[np.ndarray, np.ndarray], a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        m, s1, s2 = np.zeros(k + 1), np.zeros(k + 1), np.zeros(k + 1)
        for g in range(1, k + 1):
            at = z == g
            m[g], s1[g], s2[g] = at.sum() * (at.sum() - 1) / 2, t[0][at, g].sum() / 2, t[1][at, g].sum() / 2
        m[0], s1[0], s2[0] = total[0] - m[1:].sum(), total[1] - s1[1:].sum(), total[2] - s2[1:].sum()
        a, b = a.copy(), b.copy()
        for g in range(k + 1):
            if m[g] >= 1:
                a[g], b[g] = fit_beta(s1[g] / m[g], s2[g] / m[g], a[g], b[g], *limits[g], cfg.unimodal)
        return a, b, block_likelihood(m, s1, s2, a, b)

    def gain_of(z: np.ndarray, t: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
        own = z[:, None] == np.arange(k + 1)
        base = log_beta(a, b)
        out = (a - a[0]) * t[0] + (b - b[0]) * t[1] + (own.sum(0) - own) * (base[0] - base)
        out[:, (own.sum(0) == 0) | (np.arange(k + 1) == 0)] = 0.0
        return out

    touched = rounds = 0
    if opened is None:
        t = sums(np.zeros(n, np.int64), z, (np.zeros((n, k + 1)), np.zeros((n, k + 1))))
    else:
        t, touched = opened, n * int((z > 0).sum())
    a, b, best = fitted(z, t, a, b)
    history = [best]
    for rounds in range(1, cfg.max_iter + 1):
        gain = gain_of(z, t)
        if cfg.schedule == "sequential":
            nz = z.copy()
            for i in range(n):
                touched += int((nz > 0).sum())
                nz[i] = int(c.gain_of_one(i, nz, a, b).argmax())
        else:
            nz = gain.argmax(1)
        moved = np.flatnonzero(nz != z)
        if not len(moved):
            break
        nt = sums(z, nz, t)
        na, nb, now = fitted(nz, nt, a, b)
        while now < best - 1e-9 and len(moved) > 1:
            lift = gain[moved, nz[moved]] - gain[moved, z[moved]]
            moved = moved[np.argsort(-lift, kind="stable")[: len(moved) // 2]]
            half = z.copy()
            half[moved] = nz[moved]
            nz, nt = half, sums(z, half, t)
            na, nb, now = fitted(nz, nt, a, b)
        if now < best - 1e-9:
            break
        z, t, a, b, best = nz, nt, na, nb, now
        history.append(best)
    for g in range(1, k + 1):  # one entity is no group
        if (z == g).sum() < 2:
            z[z == g] = 0
    return Block(z, a, b, rounds, touched, history, whole.near)


# ---- peeling ---------------------------------------------------------------------------------------------------------


def peel_dense(w: np.ndarray, stop: str = "full") -> tuple[np.ndarray, float]:
    """(nodes kept, density) of a complete weighted graph: drop the node with the least weight inside again and again;
    density is half the inner weight over the nodes.  stop 'first_drop' ends where a removal does not raise it."""
    w = w.copy()
    np.fill_diagonal(w, 0.0)
    degree, alive = w.sum(1), np.ones(len(w), bool)
    total = degree.sum() / 2
    best, keep, order = (total / len(w) if len(w) else 0.0), len(w), []
    density = best
    for left in range(len(w) - 1, 0, -1):
        i = int(np.where(alive, degree, np.inf).argmin())
        total -= degree[i]
        alive[i] = False
        degree -= w[i]
        order.append(i)
        new = total / left
        if stop == "first_drop" and new <= density:
            order.pop()
            break
        density = new
        if new > best:
            best, keep = new, left
    gone = set(order[: len(w) - keep])
    return np.array([i for i in range(len(w)) if i not in gone], np.int64), float(best)


def peel_bipartite(rows: np.ndarray, cols: np.ndarray, weight: np.ndarray, stop: str = "full", col_weight: str = "unit") -> tuple[np.ndarray, np.ndarray, float]:
    """(row nodes, column nodes, density) of the densest remainder of a bipartite graph under greedy removal; edges to a
    column may be weighed down by the logarithm of its degree ('log')."""
    r, ri = np.unique(rows, return_inverse=True)
    c, ci = np.unique(cols, return_inverse=True)
    n = len(r) + len(c)
    both, at = np.unique(ri * len(c) + ci, return_inverse=True)  # an edge named twice is added up
    ri, ci, w = both // max(len(c), 1), both % max(len(c), 1), np.bincount(at.ravel(), weight.astype(float), len(both))
    if col_weight == "log":
        w = w / np.log(5.0 + np.bincount(ci, minlength=len(c)))[ci]
    nr = len(r)
    degree = np.bincount(np.r_[ri, ci + nr], np.r_[w, w], n)
    by_row, by_col = np.argsort(ri, kind="stable"), np.argsort(ci, kind="stable")
    row_at, col_at = np.searchsorted(ri[by_row], np.arange(nr + 1)), np.searchsorted(ci[by_col], np.arange(len(c) + 1))
    total, left, order = w.sum(), n, []
    best, keep = (total / n if n else 0.0), n
    density = best
    # a row's degree changes only when a column goes: rows stay sorted in between, and the lightest column is looked up
    queue, head, columns = np.argsort(degree[:nr], kind="stable"), 0, degree[nr:].copy()
    while left > 1:
        low = int(columns.argmin())
        row = head < len(queue) and degree[queue[head]] <= columns[low]
        i = int(queue[head]) if row else nr + low
        total -= degree[i] if row else columns[low]
        left -= 1
        new = total / left
        if stop == "first_drop" and new <= density:
            break
        order.append(i)
        density = new
        if row:
            head += 1
            e = by_row[row_at[i] : row_at[i + 1]]
            columns[ci[e]] -= w[e]
        else:
            e = by_col[col_at[low] : col_at[low + 1]]
            degree[ri[e]] -= w[e]
            columns[low] = np.inf
            rest = np.sort(queue[head:])
            queue, head = rest[np.argsort(degree[rest], kind="stable")], 0
        if new > best:
            best, keep = new, left
    gone = set(order[: n - keep])
    return np.array([r[i] for i in range(nr) if i not in gone]), np.array([c[j] for j in range(len(c)) if j + nr not in gone]), float(best)


# ---- attribute mixture -----------------------------------------------------------------------------------------------


def gaussian_topics(x: np.ndarray, k: int, rounds: int = 40) -> np.ndarray:
    """(n, k) responsibilities of a diagonal Gaussian mixture, started at k quantiles of the first principal direction."""
    mu, sd = x.mean(0), x.std(0)
    y = (x - mu) / np.where(sd > 1e-9, sd, 1.0)
    k = max(1, min(k, len(y)))
    direction = np.linalg.svd(y, full_matrices=False)[2][0] if len(y) > 1 else np.ones(y.shape[1])
    order = np.argsort(y @ direction, kind="stable")
    mean = np.stack([y[part].mean(0) for part in np.array_split(order, k)])
    var, share = np.ones_like(mean), np.full(k, 1 / k)
    for _ in range(rounds):
        d = -0.5 * (((y[:, None, :] - mean) ** 2 / var) + np.log(var)).sum(2) + np.log(share)
        resp = np.exp(d - d.max(1, keepdims=True))
        resp /= resp.sum(1, keepdims=True)
        size = resp.sum(0) + 1e-9
        mean = resp.T @ y / size[:, None]
        var = np.maximum(np.stack([(resp[:, j, None] * (y - mean[j]) ** 2).sum(0) / size[j] for j in range(k)]), 1e-3)
        share = size / size.sum()
    return resp
