"""Array kernels that run inside Arrow-batched tasks; plain numpy, no Spark."""

from __future__ import annotations

import numpy as np


CELLS = 4_000_000  # distances that are held at a time
COLUMNS = 16_384
GROUP = 64  # sources whose paths are found together
ARCS = 8_192  # of these paths that are sent on at a time
DENSE_ROWS = 1_000  # of a table whose pairs are all worked out
KRYLOV = 240  # directions that block steps gather before they begin again from the best
TILE = 2_048  # points of a tile of rough distances
ROUGH = 2.0**-23
SPARE = 24  # columns of a block beyond the pairs that are asked for


def squared_distances(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """(queries, points), by differences and not by products, so that near points lose no digits."""
    out = np.zeros((len(q), len(x)))
    for k in range(x.shape[1]):
        out += np.subtract.outer(q[:, k], x[:, k]) ** 2
    return out


def distances(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """(queries, points), by matrix products; pairs so near that these lose digits, by differences."""
    middle = x.mean(0) if len(x) else 0.0
    a, b = q - middle, x - middle
    size = (a**2).sum(1)[:, None] + (b**2).sum(1)
    out = size - 2 * (a @ b.T)
    if not np.isfinite(size).all():  # lengths overflow
        return np.sqrt(squared_distances(q, x))
    near = np.flatnonzero((out <= 1e-2 * size).ravel())
    for at in range(0, len(near), CELLS // 64):
        i, j = np.divmod(near[at : at + CELLS // 64], len(x))
        out[i, j] = sum((q[i, k] - x[j, k]) ** 2 for k in range(x.shape[1]))
    return np.sqrt(out)


def rank_in_row(row: np.ndarray) -> np.ndarray:
    """The place of each entry within its run of equal values; ``row`` ascends."""
    first = np.r_[True, row[1:] != row[:-1]] if len(row) else np.zeros(0, bool)
    return np.arange(len(row)) - np.maximum.accumulate(np.where(first, np.arange(len(row)), 0))


def few_copies(x: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of x without those copies of a vector that at least k + 1 copies with smaller ids stand before: no k nearest rows have them."""
    if len(x) <= k + 1:
        return np.arange(len(x))
    key = x @ np.random.default_rng(0).standard_normal(x.shape[1])
    order = np.argsort(key, kind="stable")
    o = x[order]
    run = np.cumsum(np.r_[True, (o[1:] != o[:-1]).any(1)])
    if np.bincount(run).max() <= k + 1:
        return np.arange(len(x))
    order = order[np.lexsort((ids[order], run))]
    return np.sort(order[rank_in_row(run) <= k])


def nearest(q: np.ndarray, x: np.ndarray, ids: np.ndarray, k: int, own: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(places in x, distances) of each query's k nearest rows, ties to the smaller id; ``own``: ids that a query may not take.

    Rough distances by matrix products, at most CELLS at a time, choose candidates; these are then compared by their differences.
    """
    k = min(k, len(x) - (own is not None))
    if k <= 0 or not len(q):
        return np.zeros((len(q), 0), np.int64), np.zeros((len(q), 0))
    kept = few_copies(x, ids, k)
    whole = len(kept) == len(x)
    x, ids = (x, ids) if whole else (x[kept], ids[kept])
    square = (x**2).sum(1)
    step = max(1, CELLS // min(len(x), COLUMNS))
    parts = [_nearest(q[at : at + step], x, square, ids, k, None if own is None else own[at : at + step]) for at in range(0, len(q), step)]
    places, dists = (np.concatenate([p[i] for p in parts]) for i in (0, 1))
    return places if whole else kept[places], dists


def _nearest(q, x, square, ids, k, own):
    m, wide = len(q), min(len(x), k + 8)
    slack = 1e-9 + 1e-13 * ((q**2).sum(1) + square.max())
    cut, row, at, value = np.full(m, np.inf), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    for c in range(0, len(x), COLUMNS):
        rough = square[c : c + COLUMNS] - 2 * (q @ x[c : c + COLUMNS].T)
        if own is not None:
            rough[ids[None, c : c + COLUMNS] == own[:, None]] = np.inf
        if not c:
            w = min(wide, rough.shape[1])
            cut = np.partition(rough, w - 1, axis=1)[:, w - 1] if w == wide else cut
        r, p = np.nonzero(rough <= (cut + slack)[:, None])
        row, at, value = np.r_[row, r], np.r_[at, p + c], np.r_[value, rough[r, p]]
        if c and len(r):
            order = np.lexsort((value, row))
            row, at, value = row[order], at[order], value[order]
            last = rank_in_row(row) == wide - 1
            cut[row[last]] = np.minimum(cut[row[last]], value[last])
            keep = value <= (cut + slack)[row]
            row, at, value = row[keep], at[keep], value[keep]
    few = np.flatnonzero(np.bincount(row, minlength=m) < k)  # numbers so large that products overflow
    if len(few):
        keep = ~np.isin(row, few)
        row, at = np.r_[row[keep], np.repeat(few, len(x))], np.r_[at[keep], np.tile(np.arange(len(x)), len(few))]
    d = np.concatenate([np.sqrt(((x[at[i : i + CELLS // 64]] - q[row[i : i + CELLS // 64]]) ** 2).sum(1)) for i in range(0, len(row), CELLS // 64)])
    if own is not None:
        d[ids[at] == own[row]] = np.inf
    order = np.lexsort((ids[at], np.round(d, 12), row))
    order = order[rank_in_row(row[order]) < k]
    return at[order].reshape(m, k), d[order].reshape(m, k)


class Held:
    """Points in blocks, all of them at hand, searched for nearest ones block by block: rough distances in single precision, of tiles that stay in the cache, choose candidates; these are compared by their differences.

    ``first``: where each block begins in ``ids`` and ``x``, and their length. Single precision errs by at most ROUGH of the squared lengths for each dimension, and so much more is let through.
    """

    def __init__(self, ids: np.ndarray, x: np.ndarray, first: np.ndarray):
        self.ids, self.x, self.first, self.rough = ids, x, first, None
        self.middle = x.mean(0) if len(x) else np.zeros(x.shape[1])
        self.scale = max((float(np.abs(x[a:b] - self.middle).max(initial=0.0)) for a, b in zip(first[:-1], first[1:], strict=True)), default=0.0) or 1.0

    def _scaled(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        z = (x - self.middle) / self.scale
        return z, (z**2).sum(1)

    def _single(self) -> None:
        """The blocks in single precision, made where they are searched."""
        self.rough, self.most = [], []
        for a, b in zip(self.first[:-1], self.first[1:], strict=True):
            z, square = self._scaled(self.x[a:b])
            self.rough.append(np.column_stack([-2 * z, square]).astype(np.float32))
            self.most.append(square.max(initial=0.0))

    def nearest(self, q: np.ndarray, own: np.ndarray, k: int, order: np.ndarray, gaps: np.ndarray, reach: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(rows of q, ids, distances), in order, of each row's k nearest but itself, ties to the smaller id. order: blocks as they are visited; a row leaves out those whose gap (rows, blocks) is more than its kth distance so far, or than its ``reach`` from the first, beyond which nothing is wanted."""
        if self.rough is None:
            self._single()
        z, square = self._scaled(q)
        single = np.column_stack([z, np.ones(len(q))]).astype(np.float32)
        row, at, dist = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        reach = np.full(len(q), np.inf) if reach is None else reach * (1 + 1e-9) + 1e-12
        wanted = reach.copy()
        found, pending, tie = [], 0, 2e-12
        for b in order:
            live = np.flatnonzero(gaps[:, b] <= reach * (1 + 1e-9) + 1e-12)
            mine, points = single[live], self.rough[b]
            slack = ROUGH * (len(self.middle) + 3) * (square[live] + 2 * self.most[b]) + 4 * tie * len(self.middle) / self.scale
            for start in range(0, len(points) if len(live) else 0, TILE):
                rough = mine @ points[start : start + TILE].T
                cut = ((reach[live] + tie) / self.scale) ** 2 * (1 + 1e-9) - square[live] + slack
                if not len(row) and not found and rough.shape[1] > k:  # nothing is known yet: the kth of this tile
                    other = np.where(self.ids[self.first[b] + start :][: rough.shape[1]] == own[live][:, None], np.float32(np.inf), rough)
                    cut = np.minimum(cut, np.partition(other, k - 1, axis=1)[:, k - 1] + 2 * slack)
                hit = np.flatnonzero((rough <= np.nextafter(cut.astype(np.float32), np.float32(np.inf))[:, None]).ravel())
                if len(hit):
                    found.append((live[hit // rough.shape[1]], hit % rough.shape[1] + start + self.first[b]))
                    pending += len(hit)
                if found and (not len(row) or pending > 4 * k * len(q)):
                    row, at, dist = self._best(q, own, k, row, at, dist, found)
                    last = rank_in_row(row) == k - 1
                    reach[row[last]] = np.minimum(reach[row[last]], dist[last])
                    found, pending = [], 0
        if found:
            row, at, dist = self._best(q, own, k, row, at, dist, found)
        near = dist <= wanted[row]
        return row[near], self.ids[at[near]], dist[near]

    def _best(self, q, own, k, row, at, dist, found):
        new_row, new_at = (np.concatenate([f[i] for f in found]) for i in (0, 1))
        new = self.ids[new_at] != own[new_row]
        new_row, new_at = new_row[new], new_at[new]
        d = [np.sqrt(((self.x[new_at[i : i + CELLS // 64]] - q[new_row[i : i + CELLS // 64]]) ** 2).sum(1)) for i in range(0, len(new_row), CELLS // 64)]
        row, at, dist = np.r_[row, new_row], np.r_[at, new_at], np.concatenate([dist, *d])
        order = np.lexsort((self.ids[at], np.round(dist, 12), row))
        order = order[rank_in_row(row[order]) < k]
        return row[order], at[order], dist[order]


def pairs_within(q: np.ndarray, x: np.ndarray, r: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(rows of q, rows of x, distance) of all pairs at most r apart."""
    square, out = (x**2).sum(1), []
    step = max(1, CELLS // max(1, len(x)))
    for at in range(0, len(q), step):
        part = q[at : at + step]
        own = (part**2).sum(1)
        slack = 1e-9 + 1e-13 * (own + square.max(initial=0))
        row, place = np.nonzero(square - 2 * (part @ x.T) <= (r * r - own + slack)[:, None])
        d = np.sqrt(sum((x[place, k] - part[row, k]) ** 2 for k in range(x.shape[1])))
        keep = d <= r
        out.append((row[keep] + at, place[keep], d[keep]))
    return tuple(np.concatenate([o[i] for o in out]) for i in range(3)) if out else (np.zeros(0, int), np.zeros(0, int), np.zeros(0))


def extreme_pairs(q: np.ndarray, x: np.ndarray, qi: np.ndarray, xi: np.ndarray, wanted: dict[int, int], held: dict[int, tuple], digits: int = 9, ascending: bool = False) -> None:
    """Updates ``held`` by the pairs of q and x: sign to (distances, ids, ids), in order, of the ``wanted[sign]`` nearest (sign 1) or farthest (-1) pairs.

    Distances that agree to ``digits`` are ties, to the smaller ids. ascending: only pairs whose second id is the larger one.
    """
    square = (x**2).sum(1)
    step = max(1, CELLS // max(1, len(x)))
    for at in range(0, len(q), step):
        part, ids = q[at : at + step], qi[at : at + step]
        rough = (part**2).sum(1)[:, None] + square - 2 * (part @ x.T)
        size = 1e-13 * (rough.max(initial=0) + square.max(initial=0) * 4)
        off = xi[None, :] <= ids[:, None] if ascending else None
        for sign, n in wanted.items():
            v = rough if sign == 1 else -rough
            if off is not None:
                v = np.where(off, np.inf, v)
            if not n or not v.size:
                continue
            have = held.get(sign, (np.zeros(0), np.zeros(0, np.int64), np.zeros(0, np.int64)))
            cut = sign * have[0][-1] ** 2 if len(have[0]) == n else np.partition(v.ravel(), min(n, v.size) - 1)[min(n, v.size) - 1]
            row, place = np.nonzero((v <= cut + 4 * 10.0**-digits * (1 + np.sqrt(abs(cut))) + size) & (v < np.inf))
            d = np.round(np.sqrt(((x[place] - part[row]) ** 2).sum(1)), digits)
            d, i, j = np.r_[have[0], d], np.r_[have[1], ids[row]], np.r_[have[2], xi[place]]
            order = np.lexsort((j, i, sign * d))[:n]
            held[sign] = d[order], i[order], j[order]


def shortest_arcs(src: np.ndarray, dst: np.ndarray, dist: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The arcs by (src, dst); of parallel ones the shortest."""
    if (np.diff(src) >= 0).all() and ((src[1:] > src[:-1]) | (dst[1:] > dst[:-1])).all():
        return src, dst, dist
    order = np.lexsort((dist, dst, src))
    src, dst, dist = src[order], dst[order], dist[order]
    once = np.r_[True, (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])] if len(src) else np.zeros(0, bool)
    return src[once], dst[once], dist[once]


def shortest_paths(n: int, src: np.ndarray, dst: np.ndarray, dist: np.ndarray, sources: np.ndarray) -> np.ndarray:
    """(sources, n) path lengths over directed arcs; inf where there is no path.

    A group of sources goes together. Of the points whose lengths fell, those within a mean arc of the nearest send them on over
    all their arcs, until none falls: whole rows at once, and few of them twice if the sources lie near each other (``graph_order``).
    Arcs go by the points they reach, so many at a time as stay in the cache.
    """
    out = np.full((len(sources), n), np.inf)
    src, dst, dist = shortest_arcs(src, dst, dist)
    first = np.searchsorted(src, np.arange(n + 1))
    degree, wide = np.diff(first), dist.mean() if len(dist) else 0.0
    for at in range(0, len(sources), GROUP):
        own = sources[at : at + GROUP]
        found, key = np.full((n, len(own)), np.inf), np.full(n, np.inf)
        found[own, np.arange(len(own))] = 0.0
        key[own] = 0.0
        while (low := key.min(initial=np.inf)) < np.inf:
            u = np.flatnonzero(key <= low + wide)
            key[u] = np.inf
            k = degree[u]
            e = np.repeat(first[u] - np.cumsum(k) + k, k) + np.arange(k.sum())
            if not len(e):
                continue
            e = e[np.argsort(dst[e], kind="stable")]
            start = np.flatnonzero(np.r_[True, dst[e[1:]] != dst[e[:-1]]])
            reached, count = dst[e[start]], np.diff(np.r_[start, len(e)])
            cut = np.unique(np.r_[np.searchsorted(start, np.arange(0, len(e), ARCS)), len(start)])
            for a, b in zip(cut[:-1], cut[1:], strict=True):
                order = np.argsort(-count[a:b], kind="stable")  # those that r arcs reach come first
                many, begin, to = count[a:b][order], start[a:b][order], reached[a:b][order]
                old, arc = found.take(to, 0), e[begin]
                best = found.take(src[arc], 0)
                best += dist[arc, None]
                for r in range(1, many[0]):
                    arc = e[begin[: np.searchsorted(-many, -r)] + r]
                    paths = found.take(src[arc], 0)
                    paths += dist[arc, None]
                    np.minimum(best[: len(arc)], paths, out=best[: len(arc)])
                fell = best < old
                hit = np.flatnonzero(fell.any(1))
                if len(hit):
                    to, best, old, fell = to[hit], best[hit], old[hit], fell[hit]
                    found[to] = np.minimum(best, old)
                    best[~fell] = np.inf
                    key[to] = np.minimum(key[to], best.min(1))
        out[at : at + GROUP] = found.T
    return out


def graph_order(n: int, src: np.ndarray, dst: np.ndarray, dist: np.ndarray, landmarks: int = 4) -> np.ndarray:
    """The points in an order in which neighbours of the graph stand near each other: halved again and again by their lengths to a few far points."""
    at, far = 0, np.zeros((0, n))
    for _ in range(min(landmarks, n)):
        g = shortest_paths(n, src, dst, dist, np.array([at]))[0]
        far = np.vstack([far, np.where(g < np.inf, g, 2 * g[g < np.inf].max() + 1)])
        at = int(far.min(0).argmax())
    open_, out = [np.arange(n)], []
    while open_:
        part = open_.pop()
        if len(part) <= GROUP // 2:
            out.append(part)
            continue
        own = far[:, part]
        part = part[np.argsort(own[np.ptp(own, 1).argmax()], kind="stable")]
        open_ += [part[len(part) // 2 :], part[: len(part) // 2]]
    return np.concatenate(out) if out else np.zeros(0, np.int64)


def centred_gram(g: np.ndarray) -> np.ndarray:
    s = g**2
    return -0.5 * (s - s.mean(0) - s.mean(1)[:, None] + s.mean())


def signed(v: np.ndarray) -> np.ndarray:
    """Columns with their largest entry positive."""
    return v * np.where(v[np.abs(v).argmax(0), np.arange(v.shape[1])] < 0, -1.0, 1.0) if v.size else v


def krylov(n: int, d: int, rounds: int = 200, tolerance: float = 1e-8, seed: int = 0, start: np.ndarray | None = None):
    """Block Krylov steps for the d largest pairs of a symmetric n x n table that is never held here.

    A generator: it gives a block of columns and is sent the table's product with it; its result is (values, vectors) as
    ``top_eigen`` has them. Steps end when no pair's residual is above ``tolerance`` of the largest value; KRYLOV directions
    are held at most, then the best begin again. start: a first block near the wanted directions, else it is random.
    """
    block = np.linalg.qr(np.random.default_rng(seed).standard_normal((n, min(n, d + SPARE))) if start is None else start)[0]
    width = block.shape[1]
    basis, image, w, v = np.zeros((n, 0)), np.zeros((n, 0)), np.zeros(0), np.zeros((0, 0))
    for _ in range(rounds if n else 0):
        z = yield block
        basis, image = np.column_stack([basis, block]), np.column_stack([image, z])
        small = basis.T @ image
        w, v = np.linalg.eigh((small + small.T) / 2)
        w, v = w[::-1], v[:, ::-1]
        size = max(np.abs(w).max(), 1e-300)
        off = image @ v[:, :d] - basis @ v[:, :d] * w[:d]
        if np.sqrt((off**2).sum(0)).max(initial=0) <= tolerance * size and len(w) >= min(n, d):
            break
        rest = z - basis @ (basis.T @ z)
        rest -= basis @ (basis.T @ rest)
        left, most, _ = np.linalg.svd(rest, full_matrices=False)
        block = left[:, most > 1e-12 * size]
        if not block.shape[1]:
            break
        if basis.shape[1] + block.shape[1] > max(KRYLOV, 4 * width):
            basis, image = basis @ v[:, : 2 * width], image @ v[:, : 2 * width]
            block = np.linalg.qr(block - basis @ (basis.T @ block))[0]
    order = np.arange(min(d, len(w)))
    order = order[w[order] > max(w.max(initial=0), 0) * 1e-10]
    return w[order], signed(basis @ v[:, order])


def top_eigen(gram: np.ndarray, d: int) -> tuple[np.ndarray, np.ndarray]:
    """(values, vectors) of the d largest, positive ones only, signs made canonical. More than DENSE_ROWS rows go by block Krylov steps."""
    if len(gram) > max(DENSE_ROWS, 16 * d):
        steps = krylov(len(gram), d)
        block = next(steps)
        while True:
            try:
                block = steps.send((gram @ block + gram.T @ block) / 2)
            except StopIteration as e:
                return e.value
    value, vector = np.linalg.eigh((gram + gram.T) / 2)
    keep = np.argsort(-value)[:d]
    keep = keep[value[keep] > max(value.max(initial=0), 0) * 1e-10]
    return value[keep], signed(vector[:, keep])


def classical_scaling(g: np.ndarray, d: int) -> np.ndarray:
    """Coordinates whose distances are nearest to g; fewer than d columns are filled with zeros."""
    value, vector = top_eigen(centred_gram(g), d)
    y = vector * np.sqrt(value)
    return np.pad(y, ((0, 0), (0, d - y.shape[1])))


def procrustes(a: np.ndarray, b: np.ndarray) -> float:
    """Share of a's spread that no shift, turn, mirror and scale of b explains."""
    a, b = a - a.mean(0), b - b.mean(0)
    na, nb = (a**2).sum(), (b**2).sum()
    if na == 0 or nb == 0:
        return 1.0
    s = np.linalg.svd(a.T @ b, compute_uv=False).sum()
    return float(max(0.0, 1 - s * s / (na * nb)))


def orthonormal_rows(m: np.ndarray) -> np.ndarray:
    q, r = np.linalg.qr(m.T)
    return (q * np.sign(np.where(np.diag(r) == 0, 1, np.diag(r)))).T


def rotation(seed: int, rows: int, size: int) -> np.ndarray:
    return orthonormal_rows(np.random.default_rng(seed).standard_normal((rows, size)))
