"""NumPy kernels that run inside Arrow stages: distances, walks, hardness, mending, thinning.

One distance function serves all methods, so that counts of evaluations and times
can be compared.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterable

import numpy as np

#: Tag of a pair that no path within the vicinity connects.
NEVER = 32767


def prepare(vectors: np.ndarray, metric: str) -> np.ndarray:
    x = np.ascontiguousarray(vectors, dtype=np.float64)
    if metric == "cosine" and x.size:
        n = np.linalg.norm(x, axis=1, keepdims=True)
        x = x / np.where(n > 0, n, 1.0)
    return x


def distances(block: np.ndarray, q: np.ndarray, metric: str) -> np.ndarray:
    """Distances of prepared rows to one prepared query."""
    if metric == "l2":
        d = block - q
        return np.sqrt(np.einsum("ij,ij->i", d, d))
    return 1.0 - block @ q


def all_distances(a: np.ndarray, b: np.ndarray, metric: str) -> np.ndarray:
    if metric == "l2":
        sq = (a * a).sum(1)[:, None] + (b * b).sum(1)[None, :] - 2.0 * (a @ b.T)
        return np.sqrt(np.maximum(sq, 0.0))
    return 1.0 - a @ b.T


#: Distances that a block of queries may fill at once.
CELLS = 4 << 20


def exact_distances(x: np.ndarray, i: np.ndarray, y: np.ndarray, j: np.ndarray, metric: str, pairs: int = 1 << 14) -> np.ndarray:
    """Distances of the prepared rows x[i] and y[j], summed in order of the coordinates: equal rows are equally far, wherever they stand."""
    out = np.zeros(len(i))
    for start in range(0, len(i), pairs):
        a, b, total = x[i[start : start + pairs]], y[j[start : start + pairs]], out[start : start + pairs]
        for c in range(x.shape[1]):
            total += (a[:, c] - b[:, c]) ** 2 if metric == "l2" else a[:, c] * b[:, c]
    return np.sqrt(out) if metric == "l2" else 1.0 - out


def rough_distances(queries: np.ndarray, base: np.ndarray, metric: str, sq: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Distances by a matrix product (l2: squared), and for each query how far they may be off."""
    d = queries @ base.T
    q, b = (queries * queries).sum(1), (base * base).sum(1) if sq is None else sq
    if metric == "l2":
        d *= -2.0
        d += q[:, None]
        d += b[None, :]
        return d, 1e-13 * (q + b.max(initial=0.0)) * 4
    np.subtract(1.0, d, out=d)
    return d, 1e-13 * (1.0 + np.sqrt(q * b.max(initial=0.0)))


def kth_bounds(d: np.ndarray, k: int, slabs: int = 16) -> np.ndarray:
    """At least the k-th smallest number of each row: the k-th smallest of the minima of as many disjoint parts as there are columns in a slab."""
    width = d.shape[1] // slabs
    if width < 2 * k:
        return np.partition(d, k - 1, axis=1)[:, k - 1]
    least = d[:, :width].copy()
    for i in range(1, slabs):
        np.minimum(least, d[:, i * width : (i + 1) * width], out=least)
    return np.partition(least, k - 1, axis=1)[:, k - 1]


#: Queries that are looked up together in single precision, scores of a tile, and rows from which on that pays.
TOGETHER, TILE, MANY = 512, 1 << 20, 16_384


def single(base: np.ndarray, metric: str) -> np.ndarray:
    """Rows in single precision, whose products with a query's are the larger the nearer; for l2 with half the squared length taken off."""
    return np.hstack([base, -0.5 * (base * base).sum(1)[:, None]]).astype(np.float32) if metric == "l2" else base.astype(np.float32)


def likely(queries: np.ndarray, rows: np.ndarray, sq: np.ndarray, k: int, metric: str) -> list[np.ndarray] | None:
    """For each query the rows (``single``) that may be among its k nearest; None where single precision leaves too many of them.

    The k-th best of a share of the rows bounds the k-th best of all, and what the products may be off is allowed for.
    """
    q2, b2 = (queries * queries).sum(1), sq.max(initial=0.0)
    if not max(q2.max(initial=0.0), b2) < 1e30:
        return None
    off = (rows.shape[1] + 8) * 2.0**-23 * (np.sqrt(q2 * b2) + (b2 if metric == "l2" else 0.0)) + 1e-13 * ((q2 + b2) * 4 if metric == "l2" else 1.0 + np.sqrt(q2 * b2)) + 1e-30
    q = (np.hstack([queries, np.ones((len(queries), 1))]) if metric == "l2" else queries).astype(np.float32)
    share = rows[:: max(1, len(rows) // max(MANY, 32 * k, len(rows) // 16))]
    least = (-kth_bounds(-(q @ share.T), k) - 2 * off).astype(np.float32)
    least = np.nextafter(least, np.float32(-np.inf))
    width = max(1, TILE // len(q))
    score, ok = np.empty((len(q), width), dtype=np.float32), np.empty((len(q), width), dtype=bool)
    whose, found, value, held = [], [], [], 0
    for start in range(0, len(rows), width):
        n = min(width, len(rows) - start)
        if n < width:
            score, ok = np.empty((len(q), n), dtype=np.float32), np.empty((len(q), n), dtype=bool)
        np.matmul(q, rows[start : start + n].T, out=score)
        np.greater_equal(score, least[:, None], out=ok)
        at = np.flatnonzero(ok)
        held += len(at)
        if held > CELLS:
            return None
        value.append(score.ravel()[at])
        whose.append((at // n).astype(np.uint16))
        found.append(at % n + start)
    whose, found, value = np.concatenate(whose), np.concatenate(found), np.concatenate(value)
    order = np.argsort(whose, kind="stable")
    ends = np.cumsum(np.bincount(whose, minlength=len(q)))[:-1]
    out = []
    for some, own, e in zip(np.split(found[order], ends), np.split(value[order], ends), off.tolist(), strict=True):
        out.append(some[own >= float(np.partition(own, len(own) - k)[len(own) - k]) - 2 * e])
    return out if sum(map(len, out)) <= CELLS // 4 else None


def roughly(queries: np.ndarray, base: np.ndarray, sq: np.ndarray, k: int, metric: str) -> list[np.ndarray]:
    """The same in double precision."""
    out, step = [], max(1, CELLS // len(base))
    for start in range(0, len(queries), step):
        d, off = rough_distances(queries[start : start + step], base, metric, sq)
        for own, bound, e in zip(d, kth_bounds(d, k).tolist(), off.tolist(), strict=True):
            some = np.flatnonzero(own <= bound + 2 * e)
            held = own[some]
            out.append(some[held <= np.partition(held, k - 1)[k - 1] + 2 * e])
    return out


def nearest(base: np.ndarray, ids: np.ndarray, queries: np.ndarray, k: int, metric: str, rows32: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Row numbers and distances of the k nearest rows for each query, ties by id.

    Matrix products find who may be among them, among many rows in single precision (``rows32``, if made before); they are ordered by their
    exact distances.
    """
    k = min(k, base.shape[0])
    rows, dist = np.empty((len(queries), k), dtype=np.int64), np.empty((len(queries), k))
    if not k:
        return rows, dist
    sq, many = (base * base).sum(1), len(base) >= max(MANY, 64 * k)
    if many and rows32 is None:
        rows32 = single(base, metric)
    step = TOGETHER if many else max(1, CELLS // len(base))
    for start in range(0, len(queries), step):
        q = queries[start : start + step]
        near = likely(q, rows32, sq, k, metric) if many else None
        inner = len(q) if near is not None else max(1, CELLS // len(base))
        for i in range(0, len(q), inner):
            part = q[i : i + inner]
            own = near if near is not None else roughly(part, base, sq, k, metric)
            whose, all_near = np.repeat(np.arange(len(part)), [len(x) for x in own]), np.concatenate(own)
            exact = exact_distances(part, whose, base, all_near, metric)
            order = np.lexsort((ids[all_near], exact, whose))
            first = np.searchsorted(whose, np.arange(len(part)))
            chosen = order[first[:, None] + np.arange(k)[None, :]]
            at = slice(start + i, start + i + len(part))
            rows[at], dist[at] = all_near[chosen], exact[chosen]
    return rows, dist


def nearer(base: np.ndarray, queries: np.ndarray, bounds: np.ndarray, metric: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query number, row, distance) of all rows nearer to a query than its bound."""
    out = []
    sq, step = (base * base).sum(1), max(1, CELLS // max(len(base), 1))
    for start in range(0, len(queries), step):
        q, bound = queries[start : start + step], bounds[start : start + step]
        d, off = rough_distances(q, base, metric, sq)
        top = (bound * np.abs(bound) if metric == "l2" else bound) + off + 1e-15 * np.abs(bound)
        whose, row = np.nonzero(d <= top[:, None])
        exact = exact_distances(q, whose, base, row, metric)
        ok = exact < bound[whose]
        out.append((whose[ok] + start, row[ok], exact[ok]))
    if not out:
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64), np.zeros(0)
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


# --- greedy beam search ------------------------------------------------------------


class Walk:
    """Result of one beam search: nearest rows, distances, evaluations, hops, and all rows seen."""

    __slots__ = ("rows", "dist", "ndc", "hops", "seen")

    def __init__(self, rows, dist, ndc, hops, seen):
        self.rows, self.dist, self.ndc, self.hops, self.seen = rows, dist, ndc, hops, seen


def walk(out: list[np.ndarray], base: np.ndarray, q: np.ndarray, k: int, entries: list[int], beam: int, metric: str, dead: np.ndarray | None = None) -> Walk:
    """Beam search from the entry rows over out-neighbour lists.

    Removed rows (``dead``) are walked through but not returned; while fewer than k live rows
    are held, the beam is doubled and the walk repeated.
    """
    beam = max(beam, k)
    while True:
        seen = np.zeros(len(base), dtype=bool)
        start = list(dict.fromkeys(entries))
        seen[start] = True
        first = distances(base[start], q, metric)
        frontier = [(float(d), r) for d, r in zip(first, start, strict=True)]
        heapq.heapify(frontier)
        held = [(-d, -r) for d, r in frontier]
        heapq.heapify(held)
        while len(held) > beam:
            heapq.heappop(held)
        ndc, hops = len(start), 0
        while frontier:
            d, u = heapq.heappop(frontier)
            if d > -held[0][0] and len(held) >= min(beam, len(base)):
                break
            hops += 1
            fresh = out[u][~seen[out[u]]] if len(out[u]) else out[u]
            if not len(fresh):
                continue
            seen[fresh] = True
            ndc += len(fresh)
            for e, v in zip(distances(base[fresh], q, metric).tolist(), fresh.tolist(), strict=True):
                if len(held) < beam:
                    heapq.heappush(held, (-e, -v))
                    heapq.heappush(frontier, (e, v))
                elif e < -held[0][0]:
                    heapq.heapreplace(held, (-e, -v))
                    heapq.heappush(frontier, (e, v))
        found = sorted((-d, -r) for d, r in held)
        live = [x for x in found if dead is None or not dead[x[1]]]
        enough = len(live) >= k or beam >= len(base)
        if enough:
            live = live[:k]
            return Walk(np.array([r for _, r in live], dtype=np.int64), np.array([d for d, _ in live]), ndc, hops, np.flatnonzero(seen))
        beam = min(2 * beam, len(base))


def sweep_walk(out: list[np.ndarray], base: np.ndarray, q: np.ndarray, k: int, entries: list[int], beams: list[int], metric: str) -> list[tuple[Walk, float]]:
    """(walk, seconds) of each beam, as ``walk`` gives them, from one walk with the widest.

    While a narrow walk goes on, the widest one pops the same rows: what the narrow beam turns away is farther than its worst row, and
    that only comes nearer.  So a narrow walk ends where the popped row is farther than its worst one.  A row exactly as far
    as the worst may be kept by the one and not by the other; such a beam is walked by itself.
    """
    from bisect import bisect_left
    from time import perf_counter

    began = perf_counter()
    wanted = sorted({max(b, k) for b in beams})
    widest, n, done, tied = wanted[-1], len(base), {}, set()
    seen = np.zeros(n, dtype=bool)
    start = list(dict.fromkeys(entries))
    seen[start] = True
    frontier = [(float(d), r) for d, r in zip(distances(base[start], q, metric), start, strict=True)]
    heapq.heapify(frontier)
    held = sorted(frontier)[:widest]
    ndc, hops, at = len(start), 0, 0

    def ended(beam: int) -> None:
        best = held[:k]
        done[beam] = Walk(np.array([r for _, r in best], dtype=np.int64), np.array([d for d, _ in best]), ndc, hops, None), perf_counter() - began

    while frontier:
        d, u = heapq.heappop(frontier)
        while at < len(wanted) and len(held) >= min(wanted[at], n) and d > held[min(wanted[at], len(held)) - 1][0]:
            ended(wanted[at])
            at += 1
        if at == len(wanted):
            break
        hops += 1
        fresh = out[u][~seen[out[u]]] if len(out[u]) else out[u]
        if not len(fresh):
            continue
        seen[fresh] = True
        ndc += len(fresh)
        narrow = wanted[at:-1]
        for e, v in zip(distances(base[fresh], q, metric).tolist(), fresh.tolist(), strict=True):
            if len(held) < widest or e < held[-1][0]:
                if (place := bisect_left(held, (e,))) < len(held) and held[place][0] == e:
                    tied.update(b for b in narrow if len(held) >= b and e == held[b - 1][0])
                    place = bisect_left(held, (e, v), place)
                held.insert(place, (e, v))
                if len(held) > widest:
                    held.pop()
                heapq.heappush(frontier, (e, v))
    for beam in wanted[at:]:
        ended(beam)
    for beam in tied:
        began = perf_counter()
        done[beam] = walk(out, base, q, k, entries, beam, metric), perf_counter() - began
    return [done[max(b, k)] for b in beams]


# --- bottleneck ranks --------------------------------------------------------------


def bottleneck_ranks(arcs: np.ndarray, n_near: int, max_rank: int, early_stop: bool = True) -> np.ndarray:
    """h[i, j] for ranks 1..n_near: the least r such that a path from i to j stays within ranks 1..r.

    ``arcs`` holds (from rank, to rank), 1-based.  Reachability is one big integer a
    rank; ranks are admitted as intermediates in order, and a pair is fixed when it is first connected.
    """
    size = min(max_rank, int(arcs.max()) if len(arcs) else n_near)
    size = max(size, n_near)
    reach = [1 << i for i in range(size + 1)]
    for a, b in arcs.tolist():
        if a <= size and b <= size:
            reach[a] |= 1 << b
    h = np.full((n_near, n_near), NEVER, dtype=np.int32)
    near = ((1 << (n_near + 1)) - 1) & ~1
    missing = n_near * n_near
    for i in range(1, n_near + 1):  # paths without an intermediate rank
        bits = reach[i] & near
        for j in range(1, n_near + 1):
            if bits >> j & 1:
                h[i - 1, j - 1] = max(i, j)
                missing -= 1
    for r in range(1, size + 1):
        through = reach[r]
        for i in range(1, size + 1):
            if not reach[i] >> r & 1:
                continue
            gain = through & ~reach[i]
            if not gain:
                continue
            reach[i] |= gain
            if i <= n_near:
                gain &= near
                while gain:
                    low = gain & -gain
                    j = low.bit_length() - 1
                    h[i - 1, j - 1] = max(i, j, r)
                    missing -= 1
                    gain ^= low
        if early_stop and not missing:
            break
    return h


def reachable_counts(arcs: np.ndarray, size: int) -> list[int]:
    """Ranks that each rank of a vicinity reaches, itself included."""
    reach = [1 << i for i in range(size)]
    for a, b in arcs.tolist():
        reach[a - 1] |= 1 << (b - 1)
    for r in range(size):
        for i in range(size):
            if reach[i] >> r & 1:
                reach[i] |= reach[r]
    return [x.bit_count() for x in reach]


# --- mending -----------------------------------------------------------------------


def mend_pairs(h: np.ndarray, gaps: np.ndarray, reach_cap: int, order: str = "length", seed: int = 0, credit=None) -> list[tuple[int, int, int]]:
    """Arcs (from, to, hardness) to add, in 0-based ranks, so that all pairs are within ``reach_cap``.

    Bad pairs are visited by increasing distance between their vectors (``length``) or in hash order
    (``random``).  An arc is taken if its pair is still bad, and the relation is then closed
    through it.  ``credit(s, t, h)`` may refuse an arc; a refused one closes nothing.
    """
    n = len(h)
    ok = [sum(1 << j for j in range(n) if h[i, j] <= reach_cap) for i in range(n)]
    full = (1 << n) - 1
    bad = [(i, j) for i in range(n) for j in range(n) if i != j and not ok[i] >> j & 1]
    if order == "random":
        from hashlib import md5

        bad.sort(key=lambda p: md5(f"{seed}:{p[0]}:{p[1]}".encode()).digest())
    else:
        bad.sort(key=lambda p: (gaps[p], p))
    arcs = []
    for s, t in bad:
        if ok[s] >> t & 1:
            continue
        if credit is not None and not credit(s, t, int(h[s, t])):
            continue
        arcs.append((s, t, int(h[s, t])))
        for i in range(n):
            if ok[i] >> s & 1:
                ok[i] |= ok[t]
        if all(x == full for x in ok):
            break
    return arcs


def lune_arcs(gaps: np.ndarray) -> list[tuple[int, int]]:
    """Relative neighbourhood arcs among a few vectors: no third one is nearer to both ends."""
    n = len(gaps)
    return [(i, j) for i in range(n) for j in range(n) if i != j and not np.any(np.maximum(gaps[i], gaps[j]) < gaps[i, j])]


def thin(to_origin: np.ndarray, between: np.ndarray, cap: int, slack: float = 0.0) -> list[int]:
    """Monotone thinning of candidates in order of their distance to the origin.

    A candidate stays if no kept one is as near or nearer to it than the origin is; with ``slack``, one is
    dropped only if a kept one is nearer by three times the slack.
    """
    kept: list[int] = []
    for v in range(len(to_origin)):
        if len(kept) >= cap:
            break
        near = between[v, kept]
        drop = np.any(near < to_origin[v] - 3 * slack) if slack else np.any(near <= to_origin[v])
        if not drop:
            kept.append(v)
    return kept


def thin_exact(origin: np.ndarray, x: np.ndarray, ids: np.ndarray, metric: str, cap: int) -> tuple[np.ndarray, np.ndarray]:
    """(rows kept, their distances) of the monotone thinning of rows x around an origin.

    Each step keeps the nearest row that is left and drops what is as near to it as to the origin; close calls go by exact distances.
    """
    d, left, kept, zero = distances(x, origin, metric), np.arange(len(x)), [], np.zeros(len(x), dtype=np.int64)
    off = 1e-12 * (1.0 + np.abs(d).max(initial=0.0))
    while len(left) and len(kept) < cap:
        own = d[left]
        first = left[own <= own.min() + off]
        v = int(first[np.lexsort((ids[first], exact_distances(x, first, origin[None, :], zero[: len(first)], metric)))[0]])
        kept.append(v)
        more = distances(x[left], x[v], metric) - own
        stay = more > 0
        close = np.flatnonzero(np.abs(more) <= off)
        at = left[close]
        stay[close] = exact_distances(x, at, x, np.full(len(at), v), metric) > exact_distances(x, at, origin[None, :], zero[: len(at)], metric)
        stay &= left != v
        left = left[stay]
    kept = np.array(kept, dtype=np.int64)
    return kept, exact_distances(x, kept, origin[None, :], zero[: len(kept)], metric)


def thin_rows(origin: int, cands: np.ndarray, base: np.ndarray, metric: str, cap: int, slack: float = 0.0) -> np.ndarray:
    """Thinned out-neighbours of a row."""
    cands = np.unique(cands[cands != origin])
    if not len(cands):
        return cands
    d = distances(base[cands], base[origin], metric)
    cands = cands[np.lexsort((cands, d))]
    d = np.sort(d)
    return cands[thin(d, all_distances(base[cands], base[cands], metric), cap, slack)]


# --- base graphs -------------------------------------------------------------------


def medoid(base: np.ndarray, metric: str) -> int:
    return int(np.argmin(distances(base, prepare(base.mean(axis=0, keepdims=True), metric)[0], metric)))


def symmetric(lists: list[np.ndarray], base: np.ndarray, metric: str, cap: int, slack: float = 0.0) -> list[np.ndarray]:
    """Lists with their reverse arcs, thinned again where they pass the cap."""
    back: list[list[int]] = [[] for _ in lists]
    for u, own in enumerate(lists):
        for v in own.tolist():
            back[v].append(u)
    both = (np.union1d(own, np.array(back[u], dtype=np.int64)).astype(np.int64) for u, own in enumerate(lists))
    return [capped(u, own, base, metric, cap, slack) for u, own in enumerate(both)]


def capped(u: int, own: np.ndarray, base: np.ndarray, metric: str, cap: int, slack: float = 0.0) -> np.ndarray:
    return thin_rows(u, own, base, metric, cap, slack) if len(own) > cap else own


def knn_lists(base: np.ndarray, ids: np.ndarray, k: int, metric: str, block: int = 512, of: np.ndarray | None = None) -> list[np.ndarray]:
    """Neighbour lists of all rows, or of those asked for."""
    lists, of = [], np.arange(len(base)) if of is None else of
    rows32 = single(base, metric) if len(base) >= MANY else None
    for i in range(0, len(of), block):
        own = of[i : i + block]
        rows, _ = nearest(base, ids, base[own], k + 1, metric, rows32)
        lists += [r[r != u][:k] for u, r in zip(own.tolist(), rows, strict=True)]
    return lists


def layered(base: np.ndarray, ids: np.ndarray, m: int, ef: int, metric: str, layers: bool) -> list[tuple[int, list[np.ndarray]]]:
    """Navigable small-world layers by bulk thinning: (layer, lists); layer 0 has at most 2m arcs a row."""
    out = [(0, symmetric([thin_rows(u, c, base, metric, m) for u, c in enumerate(knn_lists(base, ids, ef, metric))], base, metric, 2 * m))]
    return out + upper_layers(base, ids, m, ef, metric) if layers else out


def upper_layers(base: np.ndarray, ids: np.ndarray, m: int, ef: int, metric: str) -> list[tuple[int, list[np.ndarray]]]:
    """Layers above the bottom one; a row is on layer 1 and above with chance 1 / m."""
    from hashlib import md5

    out = []
    level = [int(-math.log((int(md5(str(i).encode()).hexdigest()[:8], 16) + 0.5) / 2**32) / math.log(max(m, 2))) for i in ids.tolist()]
    for layer in range(1, max(level, default=0) + 1):
        rows = np.flatnonzero(np.array(level) >= layer)
        part = base[rows]
        lists = symmetric([thin_rows(u, c, part, metric, m) for u, c in enumerate(knn_lists(part, ids[rows], ef, metric))], part, metric, m)
        full = [np.zeros(0, dtype=np.int64)] * len(base)
        for r, own in zip(rows.tolist(), lists, strict=True):
            full[r] = rows[own]
        out.append((layer, full))
    return out


def grow_tree(lists: list[np.ndarray], base: np.ndarray, root: int, metric: str, block: int = 256) -> list[np.ndarray]:
    """Make every row reachable from the root: attach the first lost row to its nearest reachable one, and go on from it.

    Distances to what is reachable are found for a block of lost rows at once, and then to what each attached row adds.
    """
    lists = list(lists)
    seen = np.zeros(len(base), dtype=bool)

    def reach(u: int) -> np.ndarray:
        seen[u] = True
        queue = [u]
        for x in queue:
            own = lists[x]
            fresh = own[~seen[own]] if len(own) else own
            if len(fresh):
                fresh = np.unique(fresh)
                seen[fresh] = True
                queue += fresh.tolist()
        return np.array(sorted(queue), dtype=np.int64)

    reach(root)
    lost = np.flatnonzero(~seen)
    while len(lost):
        some = lost[:block]
        gap, to = np.full(len(some), np.inf), np.zeros(len(some), dtype=np.int64)

        def look(rows: np.ndarray) -> None:
            step = max(1, CELLS // len(some))
            for i in range(0, len(rows), step):
                part = rows[i : i + step]
                d = all_distances(base[some], base[part], metric)
                best = np.argmin(d, axis=1)
                new = d[np.arange(len(some)), best]
                better = (new < gap) | (new == gap) & (part[best] < to)
                gap[better], to[better] = new[better], part[best][better]

        look(np.flatnonzero(seen))
        for n, v in enumerate(some.tolist()):
            if not seen[v]:
                lists[to[n]] = np.append(lists[to[n]], v)
                look(reach(v))
        lost = lost[~seen[lost]]
    return lists


def spread_row(u: int, knn: list[np.ndarray], base: np.ndarray, root: int, c: int, beam: int, r: int, metric: str, slack: float = 0.0) -> np.ndarray:
    """Thinned candidates of a row from the neighbour list and a walk from the root."""
    w = walk(knn, base, base[u], min(beam, len(base)), [root], beam, metric)
    near = np.union1d(w.rows, knn[u])
    d = distances(base[near], base[u], metric)
    return thin_rows(u, near[np.argsort(d, kind="stable")[: max(c, r)]], base, metric, r, slack)


def spreading(base: np.ndarray, ids: np.ndarray, c: int, beam: int, r: int, metric: str, slack: float = 0.0) -> tuple[list[np.ndarray], int]:
    """Navigating graph from one root: candidates from the neighbour list and a walk from the root, thinned, then grown to a tree."""
    knn = knn_lists(base, ids, min(c, max(len(base) - 1, 1)), metric)
    root = medoid(base, metric)
    lists = [spread_row(u, knn, base, root, c, beam, r, metric, slack) for u in range(len(base))]
    return grow_tree(symmetric(lists, base, metric, r, slack), base, root, metric), root


def bridge_pairs(base: np.ndarray, ids: np.ndarray, block: np.ndarray, n_near: int, metric: str) -> np.ndarray:
    """(row, candidate) pairs of a block of history: a query's nearest row and its other neighbours, both ways, each once."""
    if not len(block):
        return np.zeros((0, 2), dtype=np.int64)
    rows, _ = nearest(base, ids, block, n_near, metric)
    one, other = np.repeat(rows[:, 0], rows.shape[1] - 1), rows[:, 1:].ravel()
    code = np.unique(np.concatenate([one * len(base) + other, other * len(base) + one]))
    return np.stack([code // len(base), code % len(base)], axis=1)


def widened(u: int, lists: list[np.ndarray], base: np.ndarray, root: int, m: int, beam: int, metric: str) -> np.ndarray:
    """A row's list with the thinned rows that a walk from the root finds."""
    w = walk(lists, base, base[u], min(beam, len(base)), [root], beam, metric)
    return np.union1d(lists[u], thin_rows(u, w.rows, base, metric, m)).astype(np.int64)


def query_bridge(base: np.ndarray, ids: np.ndarray, history: np.ndarray | Iterable[np.ndarray], n_near: int, m: int, beam: int, metric: str) -> list[np.ndarray]:
    """Bipartite history graph projected on the base: a query's nearest row takes its other neighbours as candidates.

    The history is one array or an iterable of blocks, whose candidates add up before they are thinned.
    """
    cands: list[set[int]] = [set() for _ in range(len(base))]
    for block in [history] if isinstance(history, np.ndarray) else history:
        for u, v in bridge_pairs(base, ids, block, n_near, metric).tolist():
            cands[u].add(v)
    lists = [thin_rows(u, np.array(sorted(c), dtype=np.int64), base, metric, m) for u, c in enumerate(cands)]
    root = medoid(base, metric)
    lists = grow_tree(lists, base, root, metric)
    wide = [widened(u, lists, base, root, m, beam, metric) for u in range(len(base))]
    return grow_tree(symmetric(wide, base, metric, 2 * m), base, root, metric)


def greedy_tree(arcs: np.ndarray, size: int, targets: int) -> tuple[int, int]:
    """(arcs used, targets reached) of a tree grown from rank 1 that reaches ranks 1..targets.

    Each step attaches the unreached target with the shortest path from the tree, the nearer rank
    where paths are equally long; targets that no path reaches are left.
    """
    out: list[list[int]] = [[] for _ in range(size)]
    for a, b in sorted({(int(a), int(b)) for a, b in arcs}):
        out[a - 1].append(b - 1)
    tree, used = {0}, 0
    while True:
        before = dict.fromkeys(tree, -1)
        level, hit = sorted(tree), None
        while level and hit is None:
            fresh = []
            for u in level:
                for v in out[u]:
                    if v not in before:
                        before[v] = u
                        fresh.append(v)
            hit = min((v for v in fresh if v < targets), default=None)
            level = fresh
        if hit is None:
            return used, sum(v < targets for v in tree)
        while hit not in tree:
            tree.add(hit)
            used += 1
            hit = before[hit]
