"""Correlations of one window without its matrix: entities with equal rows are kept once and counted, and products are made
tile by tile.  The results are those of all entities; memory is bounded whatever their number."""

from __future__ import annotations

from functools import cached_property

import numpy as np

from . import kernels as K

#: Rows and columns of a tile, and bytes of the upper triangle's tiles that are kept for the next product.
TILE, KEEP = 512, 96 << 20
#: Distinct rows up to which the exact solver has their matrix.
EXACT = 512
#: Entries up to which distinct rows are an array.
DENSE = 8 << 20


class Sparse:
    """Rows of an (n, m) matrix by their entries: idx and val of row i are at ptr[i] : ptr[i + 1]."""

    def __init__(self, row: np.ndarray, col: np.ndarray, val: np.ndarray, n: int, m: int) -> None:
        order = np.lexsort((col, row))
        row, self.idx, self.val = row[order], col[order].astype(np.int64), val[order].astype(float)
        first = np.r_[True, (np.diff(row) != 0) | (np.diff(self.idx) != 0)] if len(row) else np.zeros(0, bool)
        at = np.flatnonzero(first)  # a cell named twice is added up
        self.val = np.add.reduceat(self.val, at) if len(at) else self.val
        row, self.idx = row[at], self.idx[at]
        self.ptr, self.shape = np.searchsorted(row, np.arange(n + 1)), (n, m)
        self.row = row

    def __len__(self) -> int:
        return self.shape[0]

    def take(self, rows: np.ndarray) -> Sparse:
        if len(rows) == len(self) and (rows == np.arange(len(self))).all():
            return self
        length = np.diff(self.ptr)[rows]
        ptr = np.r_[0, np.cumsum(length)]
        at = np.repeat(self.ptr[:-1][rows] - ptr[:-1], length) + np.arange(ptr[-1])
        out = Sparse.__new__(Sparse)
        out.row, out.idx, out.val, out.ptr, out.shape = np.repeat(np.arange(len(rows)), length), self.idx[at], self.val[at], ptr, (len(rows), self.shape[1])
        return out

    def sums(self, power: float = 1.0, absolute: bool = False) -> np.ndarray:
        v = np.abs(self.val) if absolute else self.val
        return np.bincount(self.row, v**power, len(self))

    def spread(self) -> np.ndarray:
        """Whether a row has more than one value."""
        m, mean = self.shape[1], self.sums() / max(self.shape[1], 1)
        filled = np.diff(self.ptr)
        var = np.bincount(self.row, (self.val - mean[self.row]) ** 2, len(self)) + (m - filled) * mean**2
        return np.sqrt(var / max(m, 1)) > 1e-12

    def dense(self) -> np.ndarray:
        out = np.zeros(self.shape)
        out[self.row, self.idx] = self.val
        return out

    def dots(self, other: Sparse) -> np.ndarray:
        """(n, len(other)) products of the rows."""
        used, j = np.unique(other.idx, return_inverse=True)
        d = np.zeros((len(used) + 1, len(other)))
        d[j, other.row] = other.val
        at = np.searchsorted(used, self.idx)
        at[(at == len(used)) | (used[np.minimum(at, len(used) - 1)] != self.idx)] = len(used)
        out = np.zeros((len(self), len(other)))
        hit = np.flatnonzero(at < len(used))
        rows, lo = self.row[hit], 0
        while lo < len(hit):  # whole rows, about 16,384 entries at a time
            hi = min(lo + 16_384, len(hit))
            if hi < len(hit):
                back = int(np.searchsorted(rows, rows[hi]))
                hi = back if back > lo else int(np.searchsorted(rows, rows[lo], "right"))
            h, r = hit[lo:hi], rows[lo:hi]
            start = np.flatnonzero(np.r_[True, np.diff(r) != 0])
            out[r[start]] = np.add.reduceat(d[at[h]] * self.val[h, None], start)
            lo = hi
        return out


def equal_rows(x: np.ndarray | Sparse) -> tuple[np.ndarray, np.ndarray]:
    """(first row of each class, class of each row); classes are in order of their first rows."""
    if isinstance(x, Sparse):
        seen: dict[bytes, int] = {}
        first, of = [], np.zeros(len(x), np.int64)
        for i in range(len(x)):
            own = slice(x.ptr[i], x.ptr[i + 1])
            k = seen.setdefault(x.idx[own].tobytes() + x.val[own].tobytes(), len(seen))
            of[i] = k
            if k == len(first):
                first.append(i)
        return np.asarray(first, np.int64), of
    x = np.ascontiguousarray(x + 0.0)
    _, first, of = np.unique(x.view(np.dtype((np.void, x.dtype.itemsize * x.shape[1]))).ravel(), return_index=True, return_inverse=True)
    order = np.argsort(first)
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    return first[order], place[of.ravel()]


class Cones:
    """Some classes in an order in which like ones are neighbours, cut into tiles whose rows lie within an angle of a centre.
    Two tiles that are near enough, or far enough apart, have products of one sign only, whatever the rows: there |P| v is
    made from sums of rows, without P."""

    def __init__(self, unit: np.ndarray, at: np.ndarray) -> None:
        self.unit, self.at = unit, at
        place = np.full(len(unit), -1)
        place[at] = np.arange(len(at))
        left = np.zeros(len(unit))
        left[at] = 1.0
        own: list[tuple[np.ndarray, np.ndarray | None, np.ndarray | None]] = []
        while left.sum() > TILE and len(own) < 32:
            g = unit.T @ left
            for _ in range(3):
                g = unit.T @ (left * (unit @ _unit(g) >= 0.7))
            c = unit @ _unit(g)
            mine = np.flatnonzero((left > 0) & (c >= 0.35))
            if len(mine) < TILE // 4:
                break
            mine = mine[np.argsort(-c[mine], kind="stable")]
            own.append((mine, _unit(g), c[mine]))
            left[mine] = 0.0
        rest = np.flatnonzero(left)
        if len(rest):
            top = np.concatenate([unit[rest[lo : lo + TILE]].argmax(1) for lo in range(0, len(rest), TILE)])
            own.append((rest[np.argsort(top, kind="stable")], None, None))
        order, cuts, centres, least = [], [0], [], []
        for rows, g, c in own:
            for lo in range(0, len(rows), TILE):
                part = rows[lo : lo + TILE]
                centre = _unit(unit[part].sum(0)) if g is None else g
                order.append(part)
                cuts.append(cuts[-1] + len(part))
                centres.append(centre)
                least.append((unit[part] @ centre).min() if c is None else c[lo : lo + TILE].min())
        rows = np.concatenate(order)
        self.order, self.cuts = place[rows], cuts
        self.centre, self.angle = np.array(centres), np.arccos(np.clip(least, -1, 1))
        self.tile_of = np.empty(len(at), np.int64)
        self.tile_of[self.order] = np.repeat(np.arange(len(cuts) - 1), np.diff(cuts))

    def slices(self) -> list[slice]:
        return [slice(a, b) for a, b in zip(self.cuts, self.cuts[1:])]

    def factors(self, other: Cones, mode: str) -> np.ndarray:
        """(tiles, tiles of other): the mode's entries are so many times the signed ones; nan where signs may differ."""
        between = np.arccos(np.clip(self.centre @ other.centre.T, -1, 1))
        both = np.add.outer(self.angle, other.angle)
        f = np.full(both.shape, 1.0 if mode == "signed" else np.nan)
        if mode != "signed":
            f[between + both <= np.pi / 2 - 1e-6] = 0.0 if mode == "negative" else 1.0
            f[between - both >= np.pi / 2 + 1e-6] = 0.0 if mode == "positive" else -1.0
        return f

    def linear(self, other: Cones, f: np.ndarray, v: np.ndarray) -> np.ndarray:
        """The product of what f knows, in this one's order; v in the other's.  1 of a class with itself is not yet in it."""
        sums = np.array([self.unit[other.at[other.order[s]]].T @ v[s] for s in other.slices()])
        sums = np.nan_to_num(f) @ sums
        return np.concatenate([self.unit[self.at[self.order[s]]] @ sums[i] for i, s in enumerate(self.slices())])


def _unit(g: np.ndarray) -> np.ndarray:
    size = float(np.sqrt(g @ g))
    if size > 1e-12:
        return g / size
    out = np.zeros(len(g))
    out[:1] = 1.0
    return out


def log_sums(w: np.ndarray, weight: np.ndarray, least: float) -> np.ndarray:
    """(columns, weights): ln(w).T @ weight for entries of at least `least`; rows whose neighbours have equal weights are
    multiplied before the logarithm is taken."""
    cut = np.r_[0, np.flatnonzero((np.diff(weight, axis=0) != 0).any(1)) + 1, len(weight)]
    levels = min(int(np.log2(max(300 / max(-np.log10(least), 1e-3), 1))), 6)
    if (len(cut) - 1) * 8 > len(weight) or levels < 2:
        return np.log(w).T @ weight
    out = np.zeros((w.shape[1], weight.shape[1]))
    for lo, hi in zip(cut, cut[1:]):
        x, s = w[lo:hi], np.zeros(w.shape[1])
        for _ in range(levels):
            half = len(x) // 2
            if not half:
                break
            if len(x) % 2:
                s += np.log(x[-1])
            x = x[:half] * x[half : 2 * half]
            if half <= 64:  # a view of rows the other way round is turned when it is small
                x = np.ascontiguousarray(x)
        out += np.outer(s + np.log(x).sum(0), weight[lo])
    return out


class Weighted:
    """D^1/2 P D^1/2 of some classes, D their numbers: the largest eigenvalue is that of the matrix with all copies."""

    def __init__(self, of: Folded, at: np.ndarray, count: np.ndarray) -> None:
        self.of, self.at, self.root = of, at, np.sqrt(count.astype(float))
        self.kept: dict[tuple[int, int], np.ndarray] = {}

    def __len__(self) -> int:
        return len(self.at)

    @cached_property
    def cones(self) -> Cones | None:
        return None if self.of.unit is None or len(self.at) <= TILE else Cones(self.of.unit, self.at)

    @cached_property
    def factors(self) -> np.ndarray:
        return self.cones.factors(self.cones, self.of.mode)

    def plain(self, v: np.ndarray) -> np.ndarray:
        """P v; each tile of the upper triangle whose signs are not known is made once and used both ways."""
        n, y = len(self.at), np.zeros(len(self.at))
        if self.cones is not None:
            c, f = self.cones, self.factors
            at, v, cuts = self.at[c.order], v[c.order], c.slices()
            y = c.linear(c, f, v)
            own = np.nan_to_num(f.diagonal(), nan=0.0)
            for i, s in enumerate(cuts):
                if not np.isnan(f[i, i]):
                    u = self.of.unit[at[s]]
                    y[s] += (1.0 - own[i] * (u * u).sum(1)) * v[s]
            mixed = np.argwhere(np.triu(np.isnan(f))).tolist()
            keep = len(mixed) * TILE * TILE * 8 <= KEEP
            for i, j in mixed:
                p = self.kept.get((i, j))
                if p is None:
                    p = self.of.tile(at[cuts[i]], at[cuts[j]])
                    if keep:
                        self.kept[i, j] = p
                y[cuts[i]] += p @ v[cuts[j]]
                if j > i:
                    y[cuts[j]] += p.T @ v[cuts[i]]
            out = np.empty(n)
            out[c.order] = y
            return out
        keep = n * (n + TILE) * 4 <= KEEP
        for i in range(0, n, TILE):
            for j in range(i, n, TILE):
                p = self.kept.get((i, j))
                if p is None:
                    p = self.of.tile(self.at[i : i + TILE], self.at[j : j + TILE])
                    if keep:
                        self.kept[i, j] = p
                y[i : i + TILE] += p @ v[j : j + TILE]
                if j > i:
                    y[j : j + TILE] += p.T @ v[i : i + TILE]
        return y

    def __matmul__(self, v: np.ndarray) -> np.ndarray:
        return self.root * self.plain(self.root * v)

    def dense(self) -> np.ndarray:
        return self.of.tile(self.at, self.at) * np.outer(self.root, self.root)

    def principal(self, exact: int = 0, start: np.ndarray | None = None) -> tuple[float, np.ndarray, int]:
        """Largest eigenvalue, vector and steps; exact up to `exact` entities.  start: by class, the copies' sum.

        Exact is the dense solver, or, over EXACT distinct rows, steps until no more than rounding is left: entries are not
        negative then, and the start is positive, so it cannot miss the largest.  Signed ones are dense whatever their number."""
        if not len(self):
            return 0.0, np.zeros(0), 0
        if float((self.root**2).sum()) <= exact:
            if len(self) <= EXACT or self.of.mode == "signed":
                return K.principal(self.dense(), len(self))
            return K.lanczos(self, self.root, len(self), 1e-14)
        first = self.root if start is None or not np.any(start) else np.abs(start) / self.root
        return K.lanczos(self, first)

    def loadings(self, u: np.ndarray, lam: float) -> np.ndarray:
        """By class."""
        return np.minimum(np.abs(self.plain(self.root * u)) / np.sqrt(max(lam, 1e-300)), 1.0)


class Folded:
    """Correlations among the rows of x; constant rows have 0 with all others.  Copies are 1 with each other in every mode but
    'negative', where nothing is folded."""

    def __init__(self, x: np.ndarray | Sparse, mode: str = "abs", clamp: float = 1e-3) -> None:
        self.n, self.mode, self.clamp = len(x), mode, clamp
        fold = mode != "negative" and self.n > 1 and x.shape[1] > 0 and bool(x.spread().all() if isinstance(x, Sparse) else (x.std(1) > 1e-12).all())
        first, self.of = equal_rows(x) if fold else (np.arange(self.n), np.arange(self.n))
        self.size = len(first)
        if isinstance(x, Sparse) and self.size * x.shape[1] <= DENSE:
            x, first = x.take(first).dense(), slice(None)
        if isinstance(x, Sparse):
            self.rows, self.unit = x.take(first), None
            m, s = x.shape[1], self.rows.sums()
            q = m * self.rows.sums(2) - s * s
            self.s, self.root = s, np.sqrt(np.maximum(q, 0))
        else:
            self.unit = np.empty((self.size, x.shape[1]))
            x = x[first]
            for lo in range(0, self.size, TILE):
                c = x[lo : lo + TILE] - x[lo : lo + TILE].mean(1, keepdims=True)
                length = np.sqrt((c * c).sum(1, keepdims=True))
                self.unit[lo : lo + TILE] = np.divide(c, length, out=np.zeros_like(c), where=length > 1e-12)

    @cached_property
    def count(self) -> np.ndarray:
        return np.bincount(self.of, minlength=self.size)

    @property
    def all(self) -> Weighted:
        """Of all entities; its tiles go with it."""
        out = Weighted(self, np.arange(self.size), self.count)
        if self.unit is not None and self.size > TILE:
            out.cones = self.every.cones
        return out

    @cached_property
    def every(self) -> Weighted:
        """All classes in their order by likeness, which is made once."""
        return Weighted(self, np.arange(self.size), self.count)

    def counted(self, at: np.ndarray, weight: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(classes, their numbers) of some entities, each once or `weight` times."""
        c = np.bincount(self.of[at], weight, self.size)
        k = np.flatnonzero(c)
        return k, c[k]

    def tile(self, rows: np.ndarray, cols: np.ndarray) -> np.ndarray:
        """Correlations of classes, in the mode; 1 of a class with itself."""
        if self.unit is not None:
            p = self.unit[rows] @ self.unit[cols].T
        else:
            p, mine = np.empty((len(rows), len(cols))), self.rows.take(rows)
            for j in range(0, len(cols), 256):
                own = cols[j : j + 256]
                g = mine.dots(self.rows.take(own)) * self.rows.shape[1] - np.outer(self.s[rows], self.s[own])
                size = np.outer(self.root[rows], self.root[own])
                p[:, j : j + 256] = np.divide(g, size, out=np.zeros_like(g), where=size > 1e-12)
        np.clip(p, -1, 1, out=p)
        p = np.abs(p, out=p) if self.mode == "abs" else K.in_mode(p, self.mode)
        if len(rows) == len(cols) and (rows == cols).all():
            np.fill_diagonal(p, 1.0)
            return p
        own = np.flatnonzero(np.isin(rows, cols))  # few, if any
        i, j = np.nonzero(np.equal.outer(rows[own], cols))
        p[own[i], j] = 1.0
        return p

    def tiles(self, rows: np.ndarray, cols: np.ndarray):  # noqa: ANN201
        """(slice of rows, slice of cols, tile) over all of them."""
        for i in range(0, len(rows), TILE):
            for j in range(0, len(cols), TILE):
                yield slice(i, i + TILE), slice(j, j + TILE), self.tile(rows[i : i + TILE], cols[j : j + TILE])

    def product(self, cols: np.ndarray, v: np.ndarray) -> np.ndarray:
        """P[all classes, cols] v."""
        y = np.zeros(self.size)
        if self.unit is not None and min(self.size, len(cols)) > TILE:
            a, b = self.every.cones, Cones(self.unit, cols)
            f, w = a.factors(b, self.mode), v[b.order]
            part, mine, own = a.linear(b, f, w), a.slices(), b.slices()
            for i, j in np.argwhere(np.isnan(f)).tolist():
                part[mine[i]] += self.tile(a.order[mine[i]], cols[b.order[own[j]]]) @ w[own[j]]
            y[a.order] = part
            known = f[a.tile_of[cols], b.tile_of]
            for lo in range(0, len(cols), TILE):
                s = slice(lo, lo + TILE)
                y[cols[s]] += np.where(np.isnan(known[s]), 0.0, 1.0 - np.nan_to_num(known[s]) * (self.unit[cols[s]] ** 2).sum(1)) * v[s]
            return y
        for i, j, p in self.tiles(np.arange(self.size), cols):
            y[i] += p @ v[j]
        return y

    def inner(self, at: np.ndarray) -> Weighted:
        return Weighted(self, *self.counted(at))

    def scored(self, at: np.ndarray, exact: int = 0) -> tuple[float, np.ndarray, int]:
        """(largest eigenvalue, loadings, steps) of some entities among themselves."""
        w = self.inner(at)
        lam, u, steps = w.principal(exact)
        full = np.zeros(self.size)
        full[w.at] = w.loadings(u, lam)
        return lam, full[self.of[at]], steps

    def sampled(self, mult: np.ndarray, whole: bool = True, exact: int = 0) -> K.Sampled:
        """kernels.sampled_score of rows drawn `mult` times."""
        at = np.flatnonzero(mult)
        if not len(at):
            return K.Sampled(float("nan"), 0.0, at, mult[at], np.zeros(self.n), 0)
        w = Weighted(self, *self.counted(at, mult[at].astype(float)))
        # the exact solver's limit is on distinct rows drawn, as it was before equal ones were put together
        lam, u, steps = K.principal(w.dense(), len(w)) if len(at) <= exact else K.lanczos(w, w.root)
        load = np.minimum(np.abs(self.product(w.at, w.root * u)) / np.sqrt(max(lam, 1e-300)), 1.0)[self.of]
        if not whole:
            own = np.zeros(self.n)
            own[at] = load[at]
            load = own
        return K.Sampled(lam / float(mult.sum()), lam, at, mult[at], load, steps)

    # ---- what kernels.block_model asks for -----------------------------------------------------------------------

    def opened(self, z: np.ndarray, k: int, floor: float) -> tuple[K.Totals, tuple[np.ndarray, np.ndarray]]:
        """Totals of all pairs, and each entity's sums of ln and ln(1 - .) with the members of each group: each tile of the
        upper triangle is made once."""
        number = np.array([self.count, *(np.bincount(self.of[z == g], minlength=self.size) for g in range(1, k + 1))], float).T
        order = np.lexsort(number.T)  # equal numbers side by side, for log_sums
        logs, plain, near, one = np.zeros((2, self.size, k + 1)), 0.0, 0.0, 1 - self.clamp
        c = number[:, 0]
        for i in range(0, self.size, TILE):
            for j in range(i, self.size, TILE):
                a, b = order[i : i + TILE], order[j : j + TILE]
                p, twice = self.tile(a, b), 1 if i == j else 2
                near += twice * float(c[a] @ ((p >= floor) @ c[b]))
                w = np.clip(p, self.clamp, one, out=p)
                plain += twice * float(c[a] @ (w @ c[b]))
                for o, x in zip(logs, (w, 1 - w)):
                    o[b] += log_sums(x, number[a], self.clamp)
                    if i != j:
                        o[a] += log_sums(x.T, number[b], self.clamp)
        own = np.log(one), np.log1p(-one)  # of an entity with itself
        s1, s2 = ((float(c @ o[:, 0]) - self.n * x) / 2 for o, x in zip(logs, own))
        pairs = self.n * (self.n - 1) / 2
        t = tuple(o[self.of] - np.equal.outer(z, np.arange(k + 1)) * x for o, x in zip(logs, own))
        for x in t:
            x[:, 0] = 0.0
        return K.Totals(pairs, (plain - self.n * one) / 2, s1, s2, (near - self.n * (floor <= 1)) / 2 / max(pairs, 1)), t

    def inside(self, at: np.ndarray) -> float:
        """Sum of the correlations of the pairs of some entities."""
        k, c = self.counted(at)
        w = Weighted(self, k, c)
        return float((c @ w.plain(c.astype(float)) - len(at)) / 2)

    def logs(self, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        w = np.clip(p, self.clamp, 1 - self.clamp)
        return np.log(w), np.log1p(-w)

    def moved(self, came: np.ndarray, went: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """What entities that come and go add to each entity's sums of ln and ln(1 - .) with others."""
        d = np.bincount(self.of[came], minlength=self.size) - np.bincount(self.of[went], minlength=self.size)
        cols = np.flatnonzero(d)
        cols = cols[np.argsort(d[cols], kind="stable")]  # equal numbers side by side, for log_sums
        s = np.zeros((2, self.size))
        for j, i, p in self.tiles(cols, np.arange(self.size)):
            w = np.clip(p, self.clamp, 1 - self.clamp, out=p)
            for o, x in zip(s, (w, 1 - w)):
                o[i] += log_sums(x, d[cols[j], None].astype(float), self.clamp)[:, 0]
        out = s[0][self.of], s[1][self.of]
        for o, self_ in zip(out, self.logs(np.ones(1))):  # not with itself
            o[came] -= self_[0]
            o[went] += self_[0]
        return out

    def gain_of_one(self, i: int, z: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """kernels.gains of one entity."""
        l1, l2 = self.logs(self.tile(self.of[[i]], np.arange(self.size))[0])
        self1, self2 = (x[0] for x in self.logs(np.ones(1)))
        base, out = K.log_beta(a, b), np.zeros(len(a))
        for g in range(1, len(a)):
            at = np.flatnonzero(z == g)
            if len(at):
                c, own = np.bincount(self.of[at], minlength=self.size), z[i] == g
                out[g] = (a[g] - a[0]) * (l1 @ c - own * self1) + (b[g] - b[0]) * (l2 @ c - own * self2) + (len(at) - own) * (base[0] - base[g])
        return out

    def farthest_first(self, members: np.ndarray, k: int) -> np.ndarray:
        """kernels.farthest_first."""
        if not len(members):
            return np.zeros(0, np.int64)
        at, c = self.counted(members)
        place = np.zeros(self.size, np.int64)
        place[at] = np.arange(len(at))
        own = place[self.of[members]]
        column = lambda i: self.column(self.of[members[i]], at)[own]
        seeds = [int(self.inner(members).plain(c.astype(float))[own].argmax())]
        near = [column(seeds[0])]
        while len(seeds) < min(k, len(members)):
            far = np.max(near, 0)
            nxt = int(far.argmin())
            if far[nxt] >= 0.7:
                break
            seeds.append(nxt)
            near.append(column(nxt))
        return np.argmax(near, 0) + 1

    def column(self, of: int, at: np.ndarray) -> np.ndarray:
        """Correlations of some classes with one."""
        return np.concatenate([self.tile(at[lo : lo + TILE], np.array([of]))[:, 0] for lo in range(0, len(at), TILE)])

    def partners(self, cut: float, cols: np.ndarray, c: np.ndarray) -> np.ndarray:
        """How many of some classes, each counted c times, an entity is correlated with at least `cut`."""
        y = np.zeros(self.size)
        for i, j, p in self.tiles(np.arange(self.size), cols):
            y[i] += (p >= cut) @ c[j].astype(float)
        return y[self.of]

    def neighbourhoods(self, cut: float, k: int) -> np.ndarray:
        """kernels.neighbourhoods."""
        every = np.arange(self.size)
        z, free = np.zeros(self.n, np.int64), np.ones(self.n, bool)
        count = self.partners(cut, every, self.count) - 1
        for g in range(1, k + 1):
            degree = np.where(free, count, -1)
            top = int(degree.argmax()) if len(degree) else 0
            if not len(degree) or degree[top] < 1:
                break
            own = self.column(self.of[top], every)[self.of] >= cut
            own &= free
            own[top] = True
            z[own] = g
            free &= ~own
            count = count - self.partners(cut, *self.counted(np.flatnonzero(own)))
        return z
