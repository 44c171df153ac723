"""NumPy kernels over the matrix of one shard: pruning, building and walking neighbour graphs.

A graph is a list of integer arrays (out-neighbours, nearest first). Distances that decide an edge
are squared sums of differences in double precision; ties go to the smaller position.
"""

from __future__ import annotations

import heapq
import itertools
import math

import numpy as np

SCREEN_DIM = 16  # from so many dimensions on, single precision rules most points out
SCREEN_PAIRS = 1 << 20
ROUGH_PAIRS = 1 << 22  # products in single precision that a block of points has at once
TILED_DIM = 6  # up to so many dimensions, and
TILED_ROWS = 2048  # from so many points on, boxes of points are blocked as a whole
LEAF = 32
GROUP = 64
ROUNDS = 8  # near points that rule others out for a block at once; further ones meet what is left
HEAD = 256  # points pruned before those; twice as many in an order that distance does not decide
WINDOW = 256  # points not reached that compete for a link
BLOCK = 1 << 14
LIST_PAIRS = 1 << 23  # rough distances held at once
FEW = 32  # candidates whose mutual distances are taken at once


def sq_to(x: np.ndarray, points: np.ndarray) -> np.ndarray:
    d = points - x
    return (d * d).sum(axis=1)


def sq_pairs(points: np.ndarray) -> np.ndarray:
    d = points[:, None, :] - points[None, :, :]
    return (d * d).sum(axis=2)


def nearest_or_tied(rough: np.ndarray, k: int, rows: np.ndarray, points: np.ndarray):
    """For each row, every point whose rough squared distance may be among the k least: ties and rounding included."""
    k = min(k, rough.shape[1])
    if not k:
        return [np.zeros(0, np.int64)] * len(rough)
    finite = np.partition(rough, k - 1, axis=1)[:, k - 1]
    # the three sums of the rough form are off by a few roundings of each of their terms
    slack = 8 * points.shape[1] * np.finfo(float).eps * ((rows * rows).sum(axis=1) + (points * points).sum(axis=1).max())
    return [np.flatnonzero(r <= c + 2 * t) for r, c, t in zip(rough, finite, slack)]


def exact_lists(x: np.ndarray, k: int, block: int = 512, of: np.ndarray | None = None) -> np.ndarray:
    """The k nearest others, by (distance, position), of each point, or of those at the positions `of`."""
    n = len(x)
    k = min(k, n - 1)
    of = np.arange(n) if of is None else of
    out = np.empty((len(of), max(k, 0)), np.int64)
    norms = (x * x).sum(axis=1)
    block = max(1, min(block, LIST_PAIRS // max(n, 1)))
    for a in range(0, len(of), block):
        at = of[a : a + block]
        rows = x[at]
        rough = norms[at, None] - 2 * rows @ x.T + norms[None, :]
        rough[np.arange(len(rows)), at] = np.inf
        for i, c in enumerate(nearest_or_tied(rough, k, rows, x)):
            c = c[c != at[i]]
            d = sq_to(rows[i], x[c])
            out[a + i] = c[np.lexsort((c, d))][:k]
    return out


def greedy(x: np.ndarray, p: int, cands: np.ndarray, cos_alpha: float | None, cap: int | None = None, every: np.ndarray | None = None, visit: np.ndarray | None = None) -> list[int]:
    """Candidates of p kept in order of (distance, position): no kept one may conflict.

    cos_alpha: the angle rule; None: the lune rule (a kept point closer to both ends). every: all
    squared distances, where they are at hand. visit: keys of another order to visit the points in.
    """
    d2 = sq_to(x[p], x[cands]) if every is None else every[p, cands]
    order = np.lexsort((cands, d2 if visit is None else visit[cands]))
    cands, d2 = cands[order], d2[order]
    kept: list[int] = []
    if every is None and len(cands) <= FEW:
        dr = sq_pairs(x[cands])
        bad = (d2[:, None] < d2) & (dr < d2) if cos_alpha is None else d2[:, None] + d2 - dr > 2 * np.sqrt(d2)[:, None] * np.sqrt(d2) * cos_alpha
        free = np.ones(len(cands), bool)
        for i in range(len(cands)):
            if free[i] and (cap is None or len(kept) < cap):
                kept.append(i)
                free &= ~bad[i]
        return cands[kept].tolist()
    left = np.arange(len(cands))
    while len(left) and (cap is None or len(kept) < cap):
        c, left = left[0], left[1:]
        kept.append(c)
        # what the kept point blocks is never looked at again
        dr = sq_to(x[cands[c]], x[cands[left]]) if every is None else every[cands[c], cands[left]]
        if cos_alpha is None:
            bad = (d2[c] < d2[left]) & (dr < d2[left])
        else:
            bad = d2[c] + d2[left] - dr > 2 * np.sqrt(d2[c]) * np.sqrt(d2[left]) * cos_alpha
        left = left[~bad]
    return cands[kept].tolist()


def pruned_rows(x: np.ndarray, at, cos_alpha, visit: np.ndarray | None = None, held: dict | None = None):
    """(p, kept, d2) for each point of `at`: what greedy() keeps of all other points.

    held: what is made of the points once, kept from call to call.

    Conflicts come from products of blocks; where rounding leaves one in doubt, the sums of
    differences that greedy() takes decide. cos_alpha: one value, or one a point; None: the lune rule.
    """
    at, held = np.asarray(at), {} if held is None else held
    if x.shape[1] <= TILED_DIM and len(x) >= TILED_ROWS and visit is None and np.abs(x).max() < 1e100:
        tiles = held.get("tiles") or held.setdefault("tiles", Tiles(x))
        for p in at.tolist():
            c = cos_alpha[p] if isinstance(cos_alpha, np.ndarray) else cos_alpha
            yield p, *(_tiled(x, p, c, tiles) if c is None or c < 1 else _pruned(x, p, c, None))
        return
    if cos_alpha is None and (rough := Rough.of(x)) is not None:
        yield from _lune_rows(x, at, visit, rough)
        return
    if cos_alpha is not None and visit is None and (by := _screen(x)):
        for p, rough in _roughs(x, at, by):
            c = cos_alpha[p] if isinstance(cos_alpha, np.ndarray) else cos_alpha
            yield p, *(_screened(x, p, c, rough, *by) if c < 1 else _pruned(x, p, c, None))
        return
    for p in at.tolist():
        yield p, *_pruned(x, p, cos_alpha[p] if isinstance(cos_alpha, np.ndarray) else cos_alpha, visit)


def _screen(x):
    """(squares, points around their mean in single precision, the longest) where single precision may rule points out, else None."""
    if x.shape[1] < SCREEN_DIM or len(x) < 2:
        return None
    z = x - x.mean(axis=0)
    long = np.sqrt((z * z).sum(axis=1).max())
    return ((x * x).sum(axis=1), z.astype(np.float32), long) if 1e-15 < long < 1e15 else None  # it holds the squares


def _roughs(x, at, by):
    """(p, squared distances of all points by products)."""
    sq, block = by[0], max(1, SCREEN_PAIRS // len(x))
    for a in range(0, len(at), block):
        some = at[a : a + block]
        yield from zip(some.tolist(), sq[some][:, None] - 2 * x[some] @ x.T + sq[None, :])


def _screened(x, p, cos_alpha, rough, sq, z, long, b=32, most=256, stop=None):
    """_pruned() by the angle rule: only points that no kept one blocks in single precision get sums of differences.

    rough: squared distances by products; z: the points around their mean, in single precision; long: the longest.
    stop: end once so many are kept.
    """
    d = x.shape[1]
    eps, low = 64 * (d + 4) * np.finfo(float).eps, 4 * (d + 4) * float(np.finfo(np.float32).eps) * long
    slack = eps * (sq.max() + sq[p])
    live = np.argsort(rough)
    live = live[live != p]
    rough, y, kept, dist = rough[live], None, [], []
    while len(live) and (stop is None or sum(map(len, kept)) < stop):
        cut = min(b, len(live))
        cut = int(np.searchsorted(rough, rough[cut - 1] + 2 * slack, "right"))  # what may be as near as the last comes too
        head = live[:cut]
        u = x[head] - x[p]
        d2 = (u * u).sum(axis=1)
        order = np.lexsort((head, d2))
        head, d2, u = head[order], d2[order], u[order]
        u /= np.sqrt(np.where(d2, d2, 1.0))[:, None]
        stay = _unblocked(_conflicts(x, head, d2, u, head, d2, u, cos_alpha, eps))
        kept.append(head[stay])
        dist.append(d2[stay])
        live, rough = live[cut:], rough[cut:]
        w = u[stay & (d2 > 0)].astype(np.float32)
        if len(live) and len(w):
            over = w @ (z if y is None else y[cut:]).T
            over -= (w @ z[p])[:, None]
            over = over.max(axis=0)
            away = np.sqrt(np.maximum(rough, 0))
            over = (over[live] if y is None else over) - cos_alpha * away
            width = low + np.minimum(slack / np.maximum(away, 1e-150), np.sqrt(slack))
            bad = over > width
            for j in np.flatnonzero(np.abs(over) <= width).tolist():
                dl, dr = sq_to(x[p], x[live[j : j + 1]])[0], sq_to(x[live[j]], x[kept[-1]])
                bad[j] = (dist[-1] + dl - dr > 2 * np.sqrt(dist[-1]) * np.sqrt(dl) * cos_alpha).any()
            live, rough = live[~bad], rough[~bad]
            # gathered once fewer than half are left
            y = y[cut:][~bad] if y is not None else z[live] if 2 * len(live) < len(x) else None
        elif y is not None:
            y = y[cut:]
        b = min(2 * b, most)
    return (np.concatenate(kept), np.concatenate(dist)) if kept else (live, rough)


class Rough:
    """Points around their mean in single precision, and what products of them are off by at most."""

    def __init__(self, x, z, squares, long):
        self.z, self.squares = z.astype(np.float32), squares
        most, d = np.abs(x).max() * math.sqrt(x.shape[1]), x.shape[1] + 4
        self.slack = 4 * d * long * (float(np.finfo(np.float32).eps) * long + 2 * np.finfo(float).eps * most)
        self.exact, self.half = z, squares.astype(np.float32)

    @classmethod
    def of(cls, x) -> Rough | None:
        """None for few dimensions, and where single precision does not hold the squares."""
        if x.shape[1] < SCREEN_DIM or len(x) < 2:
            return None
        z = x - x.mean(axis=0)
        squares = (z * z).sum(axis=1)
        long = math.sqrt(squares.max())
        return cls(x, z, squares, long) if 1e-15 < long < 1e15 else None

    def distances(self, at) -> np.ndarray:
        """Squared distances of all points, less the points' own squares, to 4 slacks."""
        out = self.z[at] @ self.z.T
        out *= -2
        out += self.half
        return out

    def beyond(self, p, near):
        """Differences to points near p, and the products with them from which on another point is surely closer to these."""
        w = self.exact[near] - self.exact[p]
        return w.astype(np.float32), ((self.squares[near] - self.squares[p]) / 2 + self.slack).astype(np.float32)

    def left(self, at, near, rough=None, dist=None) -> np.ndarray:
        """(points of `at`, all points): what no point of the first ROUNDS of each list is surely closer to; with rough and dist, none that is surely nearer too."""
        alive = np.ones((len(at), len(self.z)), bool)
        for j in range(min(ROUNDS, max(map(len, near), default=0))):
            has = np.flatnonzero([len(c) > j for c in near])
            w, most = self.beyond(at[has], np.array([near[i][j] for i in has]))
            stay = w @ self.z.T <= most[:, None]
            if dist is not None:
                stay |= (rough if len(has) == len(at) else rough[has]) <= np.array([dist[i][j] for i in has], np.float32)[:, None]
            if len(has) == len(at):
                alive &= stay
            else:
                alive[has] &= stay
            if alive.mean() < 0.01:
                break
        return alive

    def less(self, p, live, near, rough=None, dist=None) -> np.ndarray:
        """What `left` leaves of the points live by whole lists, a few of a list at a time."""
        for a in range(0, len(near), ROUNDS):
            if not len(live):
                break
            w, most = self.beyond(p, near[a : a + ROUNDS])
            bad = w @ self.z[live].T > most[:, None]
            if dist is not None:
                bad &= rough[live] > dist[a : a + ROUNDS, None]
            live = live[~bad.any(axis=0)]
        return live


def _lune_rows(x, at, visit, r: Rough):
    """pruned_rows() by the lune rule: what is kept of a few points first rules most others out in single precision, for a block at once.

    By distance the few are the nearest, else the first ones. Sums of differences decide on all that is left.
    """
    n, block = len(x), max(1, ROUGH_PAIRS // len(x))
    eps, every = 64 * (x.shape[1] + 4) * np.finfo(float).eps, None if visit is None else np.lexsort((np.arange(n), visit))

    def kept_of(p, live):
        u = x[live] - x[p]
        d2 = (u * u).sum(axis=1)
        order = np.lexsort((live, d2 if visit is None else visit[live]))
        return live[order], d2[order], u[order]

    for a in range(0, len(at), block):
        some = at[a : a + block]
        rough, heads, near, dist, gone = r.distances(some), [], [], [], []
        for i, p in enumerate(some.tolist()):
            if visit is None:
                most = _few_least(rough[i], HEAD)
                head = np.flatnonzero(rough[i] <= most + 8 * r.slack)
                head, d2, u = kept_of(p, head[head != p])
                # all points up to this distance are among them
                whole = d2 <= float(most) + r.squares[p] + 4 * r.slack
                head, d2, u = head[whole], d2[whole], u[whole]
            else:
                head = every[: 2 * HEAD + 1]
                head, d2, u = kept_of(p, head[head != p])
            kept, dk = _pruned(x, p, None, visit, others=(head, d2, u))
            first = np.argsort(dk, kind="stable")
            heads.append((kept, dk))
            near.append(kept[first])
            dist.append((dk[first] - r.squares[p] + 4 * r.slack).astype(np.float32) if visit is not None else None)
            gone.append(np.append(head, p))
        by = (rough, dist) if visit is not None else ()
        alive = r.left(some, near, *by)
        for i, p in enumerate(some.tolist()):
            alive[i, gone[i]] = False
            live = r.less(p, np.flatnonzero(alive[i]), near[i], *((rough[i], dist[i]) if by else ()))
            kept, dk = heads[i]
            if len(live):
                live, d2, u = kept_of(p, live)
                stay = ~_conflicts(x, kept, dk, x[kept] - x[p], live, d2, u, None, eps, any_of=True)
                more, dm = _pruned(x, p, None, visit, others=(live[stay], d2[stay], u[stay]))
                kept, dk = np.concatenate([kept, more]), np.concatenate([dk, dm])
            yield p, kept, dk


class Tiles:
    """Points of few dimensions in boxes of LEAF or fewer, and boxes of GROUP of those that stand near each other."""

    def __init__(self, x):
        order, starts, todo = [], [0], [np.arange(len(x))]
        while todo:
            at = todo.pop()
            if len(at) <= LEAF:
                order.append(at)
                starts.append(starts[-1] + len(at))
                continue
            some = x[at]
            half = np.argpartition(some[:, int(np.ptp(some, axis=0).argmax())], len(at) // 2)
            todo += [at[half[len(at) // 2 :]], at[half[: len(at) // 2]]]
        self.order, self.starts = np.concatenate(order), np.array(starts)
        self.low, self.high = (f.reduceat(x[self.order], self.starts[:-1]) for f in (np.minimum, np.maximum))
        self.groups = np.arange(0, len(self.low), GROUP)
        self.group_low, self.group_high = np.minimum.reduceat(self.low, self.groups), np.maximum.reduceat(self.high, self.groups)

    def points(self, tiles) -> np.ndarray:
        return np.concatenate([self.order[self.starts[t] : self.starts[t + 1]] for t in tiles])


def _box_reach(p, low, high):
    """(least squared distance, offset of the middle, half the widths) of boxes, seen from a point."""
    middle, half = (low + high) / 2 - p, (high - low) / 2
    gap = np.maximum(np.abs(middle) - half, 0)
    return (gap * gap).sum(axis=1), middle, half


def _boxes_left(v, dv, middle, half, cos_alpha):
    """Boxes that the kept points, at offsets v, do not block as a whole for sure; all points in them are farther."""
    if cos_alpha is None:
        inside = 2 * (v @ middle.T - np.abs(v) @ half.T) - dv[:, None]
    else:
        far = np.abs(middle) + half
        u = v / np.sqrt(np.where(dv, dv, 1.0))[:, None]
        inside = u @ middle.T - np.abs(u) @ half.T - cos_alpha * np.sqrt((far * far).sum(axis=1))
    size = np.abs(middle).max() + half.max()
    return (inside <= 1e-9 * (size + np.sqrt(dv.max())) * (size if cos_alpha is None else 1.0)).all(axis=0)


def _tiled(x, p, cos_alpha, t: Tiles):
    """_pruned() that meets boxes from near to far, and none that the kept points block as a whole."""
    eps = 64 * (x.shape[1] + 4) * np.finfo(float).eps
    groups, (gd, gm, gh) = np.arange(len(t.groups)), _box_reach(x[p], t.group_low, t.group_high)
    tiles, td, tm, th = np.zeros(0, np.int64), np.zeros(0), np.zeros((0, x.shape[1])), np.zeros((0, x.shape[1]))
    live, d2, u = np.zeros(0, np.int64), np.zeros(0), np.zeros((0, x.shape[1]))
    kept, dist, take, wide = [], [], 6, 1
    while len(groups) or len(tiles) or len(live):
        while len(groups) and (len(tiles) <= take or gd.min() < np.partition(td, take)[take]):
            some = np.argpartition(gd, wide)[:wide] if len(groups) > wide else np.arange(len(groups))
            mine = (t.groups[groups[some]][:, None] + np.arange(GROUP)).ravel()
            mine = mine[mine < len(t.low)]
            d, m, h = _box_reach(x[p], t.low[mine], t.high[mine])
            if kept:
                open_ = _boxes_left(v, dv, m, h, cos_alpha)
                mine, d, m, h = mine[open_], d[open_], m[open_], h[open_]
            tiles, td, tm, th = np.append(tiles, mine), np.append(td, d), np.concatenate([tm, m]), np.concatenate([th, h])
            other = np.ones(len(groups), bool)
            other[some] = False
            groups, gd, gm, gh = groups[other], gd[other], gm[other], gh[other]
            wide = min(2 * wide, 64)
        if len(tiles):
            near = np.argpartition(td, take - 1)[:take] if len(tiles) > take else np.arange(len(tiles))
            new = t.points(tiles[near])
            new = new[new != p]
            w = x[new] - x[p]
            dw = (w * w).sum(axis=1)
            if kept and len(new):
                open_ = ~_conflicts(x, every, de, ve, new, dw, w if cos_alpha is None else w / np.sqrt(np.where(dw, dw, 1.0))[:, None], cos_alpha, eps, any_of=True)
                new, dw, w = new[open_], dw[open_], w[open_]
            live, d2, u = np.append(live, new), np.append(d2, dw), np.concatenate([u, w])
            other = np.ones(len(tiles), bool)
            other[near] = False
            tiles, td, tm, th = tiles[other], td[other], tm[other], th[other]
        # up to this distance no point is missing
        whole = min(td.min() if len(td) else np.inf, gd.min() if len(gd) else np.inf) * (1 - 1e-9)
        ready = np.flatnonzero(d2 < whole)
        ready = ready[np.lexsort((live[ready], d2[ready]))]
        if len(ready):
            got, dg = _pruned(x, p, cos_alpha, None, others=(live[ready], d2[ready], u[ready]))
            kept.append(got)
            dist.append(dg)
            v, dv = x[got] - x[p], dg
            every, de = np.concatenate(kept), np.concatenate(dist)
            ve = x[every] - x[p]
            ve = ve if cos_alpha is None else ve / np.sqrt(np.where(de, de, 1.0))[:, None]
            rest = d2 >= whole
            live, d2, u = live[rest], d2[rest], u[rest]
            if len(live):
                open_ = ~_conflicts(x, got, dg, v if cos_alpha is None else v / np.sqrt(np.where(dg, dg, 1.0))[:, None], live, d2, u if cos_alpha is None else u / np.sqrt(np.where(d2, d2, 1.0))[:, None], cos_alpha, eps, any_of=True)
                live, d2, u = live[open_], d2[open_], u[open_]
            if len(tiles):
                open_ = _boxes_left(v, dv, tm, th, cos_alpha)
                tiles, td, tm, th = tiles[open_], td[open_], tm[open_], th[open_]
            if len(groups):
                open_ = _boxes_left(v, dv, gm, gh, cos_alpha)
                groups, gd, gm, gh = groups[open_], gd[open_], gm[open_], gh[open_]
            v, dv = x[every] - x[p], de
        take = min(2 * take, 256)
    return (np.concatenate(kept), np.concatenate(dist)) if kept else (live, d2)


def _few_least(row: np.ndarray, k: int) -> float:
    """A value that about k of the row are up to: from a part of it, where that serves."""
    step = max(1, len(row) // (k * 32))
    some = np.sort(row[::step])
    most = some[min(len(some) - 1, max(1, k // step))]
    if not k // 4 <= np.count_nonzero(row <= most) <= 8 * k:
        k = min(k, len(row) - 1)
        most = np.partition(row, k)[k]
    return most


def _unblocked(clash: np.ndarray) -> np.ndarray:
    """Of points in the order of visits, those that no earlier one left blocks."""
    stay = np.ones(len(clash), bool)
    for i in range(len(clash)):
        if stay[i]:
            stay[i + 1 :] &= ~clash[i, i + 1 :]
    return stay


def _others(x, p, visit=None):
    """(position, squared distance, difference) of all other points, in the order of visits."""
    live = np.delete(np.arange(len(x)), p)
    u = x[live] - x[p]
    d2 = (u * u).sum(axis=1)
    order = np.lexsort((live, d2 if visit is None else visit[live]))
    return live[order], d2[order], u[order]


def _pruned(x, p, cos_alpha, visit, most=256, others=None, stop=None):
    """stop: end once so many are kept."""
    live, d2, u = _others(x, p, visit) if others is None else others
    kept, dist, b = [], [], 8
    if cos_alpha is not None:
        if cos_alpha >= 1:  # no angle is less than none
            return live, d2
        u = u / np.sqrt(np.where(d2, d2, 1.0))[:, None]
    eps = 64 * (x.shape[1] + 4) * np.finfo(float).eps
    while len(live) and (stop is None or sum(map(len, kept)) < stop):
        head, rest = slice(0, b), slice(b, None)
        stay = _unblocked(_conflicts(x, live[head], d2[head], u[head], live[head], d2[head], u[head], cos_alpha, eps))
        kept.append(live[head][stay])
        dist.append(d2[head][stay])
        past = (live[rest], d2[rest], u[rest])
        left = ~_conflicts(x, kept[-1], dist[-1], u[head][stay], *past, cos_alpha, eps, any_of=True)
        live, d2, u = (c[left] for c in past)
        b = min(2 * b, most)
    return (np.concatenate(kept), np.concatenate(dist)) if kept else (live, d2)


def _conflicts(x, c, dc, uc, l, dl, ul, cos_alpha, eps, any_of=False):
    """Whether the kept c block the l, as a table or for any c; u: differences from the point, of length one for the angle rule."""
    if not len(c) or not len(l):
        return np.zeros(len(l), bool) if any_of else np.zeros((len(c), len(l)), bool)
    if cos_alpha is not None:
        over = uc @ ul.T
        over[dc == 0] = -2.0  # copies of the point block nothing, and nothing blocks them
        far = dc[dc > 0].min() if dc.any() else 1.0
        width, over = eps * (1 + np.sqrt(dl.max() / far)), over - cos_alpha if not any_of else over.max(axis=0) - cos_alpha
    else:
        over, width = 2 * (uc @ ul.T) - dc[:, None], eps * max(dc.max(), dl.max())  # more than nothing: closer to c than to the point
        np.minimum(over, dl[None, :] - dc[:, None], out=over)
        over = over.max(axis=0) if any_of else over
    bad, open_ = over > width, np.abs(over) <= width
    # in a table only earlier points block later ones
    doubt = np.flatnonzero(open_ if any_of else np.triu(open_, 1).any(axis=0))
    some = max(1, (1 << 18) // (len(c) * x.shape[1]))
    for j in (doubt[a : a + some] for a in range(0, len(doubt), some)):
        far, apart = dl[j][:, None], x[l[j]][:, None, :] - x[c]
        dr = (apart * apart).sum(axis=2)
        sure = (dc < far) & (dr < far) if cos_alpha is None else dc + far - dr > 2 * np.sqrt(dc) * np.sqrt(far) * cos_alpha
        if any_of:
            bad[j] = sure.any(axis=1)
        else:
            bad[:, j] = sure.T
    return bad


def degree_choice(x: np.ndarray, p: int, target: int, grid, rough: np.ndarray | None = None, by=None) -> tuple[float, int] | None:
    """(alpha, degree): of (cosine, alpha) by falling alpha the one whose degree is nearest to the target, the widest of equals.

    rough, by: as for `_screened`, where single precision may rule points out.
    """
    others = _others(x, p) if by is None else None
    best, near = None, {}
    for cosine, alpha in grid:
        # degrees only rise while points are kept: at this one the angle has lost
        lost = None if best is None else target + abs(best[1] - target)
        if by is None or cosine >= 1:
            n = len(_pruned(x, p, cosine, None, others=others or _others(x, p), stop=lost)[0])
        else:
            for k in (2 * lost, 8 * lost) if lost else ():  # most lose among the nearest points already
                near[k] = near[k] if k in near else _nearest_others(x, p, k, rough, by)
                if (n := len(_pruned(x, p, cosine, None, others=near[k], stop=lost)[0])) >= lost:
                    break
            else:
                n = len(_screened(x, p, cosine, rough, *by, stop=lost)[0])
        if n and (best is None or abs(n - target) < abs(best[1] - target)):
            best = alpha, n
    return best


def _nearest_others(x, p, k, rough, by):
    """_others() of about the k nearest points, none left out up to the last."""
    sq, k = by[0], min(k, len(x) - 1)
    slack = 64 * (x.shape[1] + 4) * np.finfo(float).eps * (sq.max() + sq[p])
    most = np.partition(rough, k)[k]
    live = np.flatnonzero(rough <= most + 2 * slack)
    live = live[live != p]
    u = x[live] - x[p]
    d2 = (u * u).sum(axis=1)
    order = np.lexsort((live, d2))
    order = order[d2[order] <= most + slack]
    return live[order], d2[order], u[order]


def degree_rows(x: np.ndarray, at, target: int, grid):
    """(p, degree_choice(x, p, target, grid)) for points."""
    at, by = np.asarray(at), _screen(x)
    if by is None:
        yield from ((p, degree_choice(x, p, target, grid)) for p in at.tolist())
    else:
        yield from ((p, degree_choice(x, p, target, grid, rough, by)) for p, rough in _roughs(x, at, by))


def unreached_rows(x: np.ndarray, at, outs):
    """(p, unreached(x, p, out)) for points and their out-neighbours: near ones rule most points out for a block at once."""
    at, r = np.asarray(at), Rough.of(x)
    block = max(1, ROUGH_PAIRS // max(len(x), 1))
    for a in range(0, len(at), block):
        some, lists = at[a : a + block], outs[a : a + block]
        if r is not None:
            lists = [out[np.argsort(sq_to(x[p], x[out]), kind="stable")] for p, out in zip(some, lists)]
            alive = r.left(some, lists)
            alive[np.arange(len(some)), some] = False
        for i, (p, out) in enumerate(zip(some.tolist(), lists)):
            yield p, unreached(x, p, out) if r is None else unreached(x, p, out, r.less(p, np.flatnonzero(alive[i]), out))


def unreached(x: np.ndarray, p: int, out: np.ndarray, q: np.ndarray | None = None) -> np.ndarray:
    """Points q, of all others or those given, with no out-neighbour of p closer to q than p is."""
    q = np.delete(np.arange(len(x)), p) if q is None else q
    if not len(out) or not len(q):
        return q
    u = x[q] - x[p]
    d2, v = (u * u).sum(axis=1), x[out] - x[p]
    gain = (2 * (v @ u.T) - (v * v).sum(axis=1)[:, None]).max(axis=0)
    width = 64 * (x.shape[1] + 4) * np.finfo(float).eps * max(d2.max(), 0.0)
    far = gain < -width
    for j in np.flatnonzero(np.abs(gain) <= width).tolist():
        far[j] = sq_to(x[q[j]], x[out]).min() >= d2[j]
    return q[far]


def complete_graph(x, cos_alpha):
    """The exact graph: every other point is a candidate."""
    return [kept.tolist() for _, kept, _ in pruned_rows(x, np.arange(len(x)), cos_alpha)]


def all_pairs(x: np.ndarray) -> np.ndarray:
    return np.stack([sq_to(p, x) for p in x]) if len(x) else np.zeros((0, 0))


def violations(x: np.ndarray, graph) -> int:
    """Pairs (p, q) with no out-neighbour of p closer to q than p is."""
    table = all_pairs(x)
    bad = 0
    for p, out in enumerate(graph):
        best = table[out].min(axis=0) if out else np.full(len(x), np.inf)
        worse = best >= table[p]
        worse[p] = False
        bad += int(worse.sum())
    return bad


def two_hop(lists: np.ndarray, p: int, size: int, trim_x: np.ndarray | None = None) -> np.ndarray:
    """Neighbours and their lists, a whole block at a time, until the pool has `size` members."""
    seen: dict[int, None] = {}
    for q in lists[p].tolist():
        for c in [q, *lists[q].tolist()]:
            if c != p:
                seen.setdefault(c)
        if len(seen) >= size:
            break
    pool = np.fromiter(seen, np.int64, len(seen))
    if trim_x is not None and len(pool) > size:
        pool = pool[np.lexsort((pool, sq_to(trim_x[p], trim_x[pool])))][:size]
    return pool


def reverse_refine(x, graph, cos_alpha, cap, mode="reprune"):
    """Add back-edges where nothing kept conflicts; see the two modes of the operator."""
    incoming: list[list[int]] = [[] for _ in graph]
    for p, out in enumerate(graph):
        for q in out:
            incoming[q].append(p)
    return [refined(x, q, out, incoming[q], cos_alpha, cap, mode) for q, out in enumerate(graph)]


def refined(x, q: int, out, incoming, cos_alpha, cap, mode="reprune") -> list[int]:
    """The reverse step of one point with its out-neighbours and the points that it is an out-neighbour of."""
    have = set(out)
    extra = [p for p in incoming if p not in have]
    if not extra:
        return list(out)
    if mode == "reprune":
        return greedy(x, q, np.array(list(out) + extra), cos_alpha, cap)
    if mode != "insert":
        raise ValueError("mode is 'reprune' or 'insert'")
    kept = list(out)
    d = sq_to(x[q], x[extra])
    for i in np.lexsort((extra, d)):
        c, dk = extra[i], sq_to(x[q], x[kept])
        dr = sq_to(x[c], x[kept])
        if cos_alpha is None:
            clash = (np.minimum(dk, d[i]) < np.maximum(dk, d[i])) & (dr < np.maximum(dk, d[i]))
        else:
            clash = dk + d[i] - dr > 2 * np.sqrt(dk * d[i]) * cos_alpha
        if not clash.any():
            kept.append(c)
            dk = np.append(dk, d[i])
            if len(kept) > cap:
                kept.pop(int(np.lexsort((kept, dk))[-1]))
    return sorted(kept, key=lambda c: (float(sq_to(x[q], x[c : c + 1])[0]), c))


class Ragged:
    """Lists of positions in two arrays; `link` adds to one."""

    def __init__(self, count, to):
        self.count, self.to = np.asarray(count, np.int64), np.asarray(to, np.int32)
        self.start, self.more = np.cumsum(self.count) - self.count, {}

    @classmethod
    def of(cls, graph) -> Ragged:
        count = np.fromiter(map(len, graph), np.int64, len(graph))
        return cls(count, np.fromiter(itertools.chain.from_iterable(graph), np.int32, int(count.sum())))

    def reversed(self) -> Ragged:
        """For each position those whose lists hold it, in order."""
        order = np.argsort(self.to, kind="stable")
        return Ragged(np.bincount(self.to, minlength=len(self)), np.repeat(np.arange(len(self)), self.count)[order])

    def __len__(self):
        return len(self.count)

    def __getitem__(self, p):
        a = self.start[p]
        return self.to[a : a + self.count[p]].tolist() + self.more.get(p, [])

    def __iter__(self):
        return (self[p] for p in range(len(self)))

    def link(self, p: int, q: int) -> None:
        self.more.setdefault(p, []).append(q)


def reached(graph, root: int, seen: np.ndarray | None = None) -> np.ndarray:
    seen = np.zeros(len(graph), bool) if seen is None else seen
    todo = [root]
    seen[root] = True
    while todo:
        p = todo.pop()
        for q in graph[p]:
            if not seen[q]:
                seen[q] = True
                todo.append(q)
    return seen


def strengthen(x, graph, roots, cap) -> int:
    """Link what a root does not reach from the closest reached point with a spare edge; count the links.

    Of the first WINDOW points not reached, the one nearest to such a point is linked. Their nearest points
    are kept from link to link: only newly reached points are compared, and all where one has no spare edge left.
    """
    added, degree = 0, np.fromiter(map(len, graph), np.int64, len(graph))
    link = graph.link if isinstance(graph, Ragged) else lambda p, q: graph[p].append(q)
    norms = (x * x).sum(axis=1)
    for root in roots:
        seen = _reached_from(graph, int(root))
        outside = np.flatnonzero(~seen)
        near, at, spared = np.full(len(outside), np.inf), np.full(len(outside), -1), None
        while len(outside):
            spare = seen & (degree < cap)
            if spare.any() != spared:
                spared, at = bool(spare.any()), np.full(len(outside), -1)
            base = spare if spared else seen
            open_ = np.flatnonzero(at[:WINDOW] < 0)
            if len(open_):
                ahead = np.flatnonzero(at[: 2 * WINDOW] < 0)  # those that come into the window soon are met at once
                near[ahead], at[ahead] = _nearest_of(x, norms, outside[ahead], np.flatnonzero(base))
            d = near[:WINDOW]
            best = min((float(d[j]), int(at[j]), int(outside[j])) for j in np.flatnonzero(d == d.min()))
            link(best[1], best[2])
            degree[best[1]] += 1
            added += 1
            seen = reached(graph, best[2], seen)
            fresh = seen[outside]
            new, outside, near, at = outside[fresh], outside[~fresh], near[~fresh], at[~fresh]
            if spared and degree[best[1]] >= cap:
                at[at == best[1]] = -1
            met = np.flatnonzero(at >= 0)
            for p in (new[degree[new] < cap] if spared else new).tolist():
                d = sq_to(x[p], x[outside[met]])
                closer = (d < near[met]) | ((d == near[met]) & (p < at[met]))
                near[met[closer]], at[met[closer]] = d[closer], p
    return added


def _nearest_of(x, norms, points, base) -> tuple[np.ndarray, np.ndarray]:
    """Squared distances to, and positions of, the nearest of base, by (distance, position), for each of the points."""
    near, at = np.full(len(points), np.inf), np.full(len(points), -1)
    for lo in range(0, len(base), BLOCK):
        some = base[lo : lo + BLOCK]
        for a in range(0, len(points), 64):
            rows = x[points[a : a + 64]]
            rough = norms[points[a : a + 64], None] - 2 * rows @ x[some].T + norms[some][None, :]
            for i, c in enumerate(nearest_or_tied(rough, 1, rows, x[some])):
                d = sq_to(rows[i], x[some[c]])
                j = int(d.argmin())
                if d[j] < near[a + i]:  # blocks come by position, so of equals the first stays
                    near[a + i], at[a + i] = d[j], some[c[j]]
    return near, at


def _reached_from(graph, root: int) -> np.ndarray:
    """reached() of one root over the whole graph, a step of all points at once."""
    g = graph if isinstance(graph, Ragged) and not graph.more else Ragged.of(graph)
    to, start, count = g.to, g.start, g.count
    seen = np.zeros(len(graph), bool)
    seen[root], front = True, np.array([root])
    while len(front):
        n = count[front]
        out = to[np.repeat(start[front] - np.cumsum(n) + n, n) + np.arange(n.sum())]
        front = np.unique(out[~seen[out]])
        seen[front] = True
    return seen


def pick(ids: np.ndarray, m: int, seed: int = 0) -> np.ndarray:
    """Positions of the m smallest portable hashes."""
    h = ((ids % 2147483648) * 1103515245 + 12345 + seed * 7919) % 2147483648
    return np.lexsort((ids, h))[:m]


def walk(x, graph, query, entries, size: int, k: int, trace: list | None = None):
    """Best-first pool search: k positions, their squared distances, and the numbers of distances, expansions and hops."""
    entries = np.unique(np.asarray(entries, np.int64))
    d = sq_to(query, x[entries])
    n_dist = len(entries)
    start = int(np.lexsort((entries, d))[0])
    seen = {int(entries[start])}
    pool = [(float(d[start]), int(entries[start]))]
    todo = list(pool)
    depth = {pool[0][1]: 0}
    parent = {pool[0][1]: -1}
    expansions = 0
    while todo:
        dist, p = heapq.heappop(todo)
        if len(pool) >= size and (dist, p) > pool[-1]:
            break
        expansions += 1
        fresh = [q for q in graph[p] if q not in seen]
        if trace is not None:
            trace.append((expansions - 1, p, parent[p], depth[p], math.sqrt(dist), n_dist))
        if not fresh:
            continue
        seen.update(fresh)
        nd = sq_to(query, x[fresh])
        n_dist += len(fresh)
        worst = pool[-1] if len(pool) >= size else (math.inf, 0)
        for v, q in zip(nd.tolist(), fresh):
            if (v, q) < worst:
                depth[q], parent[q] = depth[p] + 1, p
                pool.append((v, q))
                heapq.heappush(todo, (v, q))
        pool.sort()
        del pool[size:]
    top = pool[:k]
    return [q for _, q in top], [v for v, _ in top], n_dist, expansions, depth[top[0][1]]


def nn_descent(x, ids, k: int, sample: int = 10, reverse: int = 20, rounds: int = 12, delta: float = 0.002, seed: int = 0) -> np.ndarray:
    """Approximate lists: neighbours of neighbours, forward and sampled reverse, until few change."""
    n = len(x)
    k = min(k, n - 1)
    if n <= 2 * k + 2:
        return exact_lists(x, k)
    rng = np.random.default_rng(int(ids[0]) * 31 + seed)
    lists = np.stack([rng.choice(n - 1, k, replace=False) for _ in range(n)])
    lists += lists >= np.arange(n)[:, None]
    dist = np.stack([sq_to(x[p], x[lists[p]]) for p in range(n)])
    fresh = np.ones((n, k), bool)
    for _ in range(rounds):
        back_new: list[list[int]] = [[] for _ in range(n)]
        forward_new = []
        for p in range(n):
            at = np.flatnonzero(fresh[p])[:sample]
            forward_new.append(lists[p][at])
            fresh[p][at] = False
            for q in lists[p][at]:
                if len(back_new[q]) < reverse:
                    back_new[q].append(p)
        changes = 0
        for p in range(n):
            near = np.unique(np.concatenate([lists[p], np.array(back_new[p], np.int64)]))
            news = np.concatenate([forward_new[p], np.array(back_new[p], np.int64)])
            if not len(news):
                continue
            pool = np.unique(np.concatenate([lists[near].ravel(), *[forward_new[q] for q in news[:reverse]], near]))
            pool = pool[pool != p]
            d = sq_to(x[p], x[pool])
            order = np.lexsort((pool, d))[:k]
            new = pool[order]
            old = np.isin(new, lists[p])
            changes += int((~old).sum())
            keep = dict(zip(lists[p].tolist(), fresh[p].tolist()))
            fresh[p] = [True if not o else keep[q] for o, q in zip(old, new.tolist())]
            lists[p], dist[p] = new, d[order]
        if changes < delta * n * k:
            break
    return lists


def widest(x, p: int, cands: np.ndarray, keep: int) -> list[int]:
    """The nearest candidate, then again and again the one with the largest summed angle to those chosen."""
    v = x[cands] - x[p]
    length = np.sqrt((v * v).sum(axis=1))
    u = v / np.where(length > 0, length, 1)[:, None]
    angles = np.arccos(np.clip(u @ u.T, -1, 1))
    chosen, total = [0], angles[:, 0].copy()
    free = np.ones(len(cands), bool)
    free[0] = False
    while len(chosen) < min(keep, len(cands)):
        c = int(np.where(free, total, -1).argmax())
        chosen.append(c)
        free[c] = False
        total += angles[:, c]
    return cands[chosen].tolist()


def hnsw_levels(ids: np.ndarray, m: int) -> np.ndarray:
    h = ((ids % 2147483648) * 1103515245 + 12345) % 2147483648
    return np.floor(-np.log((h + 1) / 2147483649) / math.log(max(2, m))).astype(int)


def hnsw(x, ids, m: int, ef: int, flat: bool = False):
    """Layers of graphs (bottom first) and the entry; points come in order of position."""
    level = np.zeros(len(x), int) if flat else hnsw_levels(ids, m)
    layers = [[[] for _ in range(len(x))] for _ in range(int(level.max()) + 1)]
    entry, top = 0, int(level[0])
    for p in range(1, len(x)):
        at = entry
        for lay in range(top, level[p], -1):
            at = walk(x, layers[lay], x[p], [at], 1, 1)[0][0]
        for lay in range(min(top, int(level[p])), -1, -1):
            found, *_ = walk(x, layers[lay], x[p], [at], ef, ef)
            cap = 2 * m if lay == 0 else m
            out = greedy(x, p, np.array(found), None, m)
            layers[lay][p] = out
            for q in out:
                layers[lay][q].append(p)
                if len(layers[lay][q]) > cap:
                    layers[lay][q] = greedy(x, q, np.array(layers[lay][q]), None, cap)
            at = found[0]
        if level[p] > top:
            entry, top = p, int(level[p])
    return layers, entry


def lloyd(x, k: int, rounds: int = 8, seed: int = 0) -> np.ndarray:
    k = min(k, len(x))
    rng = np.random.default_rng(seed)
    c = x[np.sort(rng.choice(len(x), k, replace=False))].copy()
    for _ in range(rounds):
        at = assign(x, c)
        for j in range(k):
            mine = x[at == j]
            if len(mine):
                c[j] = mine.mean(axis=0)
    return c


def assign(x, c) -> np.ndarray:
    return ((c * c).sum(axis=1)[None, :] - 2 * x @ c.T).argmin(axis=1)
