"""Radii and the cascade in d dimensions, on arrays.

Products of matrices choose pairs with room for rounding; what they choose is decided by distances of the vectors."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from revnn.operators.cascade import RULES, Outcome, visit_order

#: Vectors of a leaf; columns of a product; witnesses that are settled together, at first and at most; rows of a product.
LEAF, WIDE, FIRST, BLOCK, PIECE = 512, 1024, 32, 512, 128
#: Room for rounding in squared distances: of products, and of the shift to the middle.
ROOM, SHIFT = 1e-10, 1e-13


def far(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.sqrt(((a - b) ** 2).sum(axis=1))


def middle(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """The vectors from their middle, their squared lengths, the room for rounding."""
    z = x - (x.mean(axis=0) if len(x) else 0)
    norm = (z * z).sum(axis=1)
    most = norm.max(initial=0.0)
    return z, norm, float(ROOM * most + SHIFT * np.sqrt(most) * np.abs(x).max(initial=0.0) * np.sqrt(x.shape[1]))


def leaves(x: np.ndarray, most: int) -> list[np.ndarray]:
    """Parts of at most so many vectors, halved at the median of the widest coordinate."""
    out, todo = [], [np.arange(len(x))]
    while todo:
        at = todo.pop()
        if len(at) <= most:
            out.append(at)
            continue
        axis = int(np.argmax(np.ptp(x[at], axis=0)))
        at = at[np.argsort(x[at, axis], kind="stable")]
        todo += [at[: len(at) // 2], at[len(at) // 2 :]]
    return [a for a in out if len(a)]


def few_copies(x: np.ndarray, most: int) -> np.ndarray:
    """Which vectors to keep so that no more than so many equal ones are left."""
    key = (x * np.random.default_rng(1).normal(size=x.shape[1])).sum(axis=1)
    turn = np.argsort(key, kind="stable")
    new = np.ones(len(x), bool)
    new[1:] = (x[turn[1:]] != x[turn[:-1]]).any(axis=1)
    start = np.flatnonzero(new)
    keep = np.empty(len(x), bool)
    keep[turn] = np.arange(len(x)) - np.repeat(start, np.diff(np.append(start, len(x)))) < most
    return keep


def radii(x: np.ndarray, k: int, part: int, parts: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(positions, radius, distance of the nearest other) for the leaves part, part + parts, ...

    A leaf looks at the others by the distance of their boxes and ends where that exceeds its vectors' k-th distances.
    Copies of a vector beyond k + 1 change no radius and are not looked at."""
    groups = leaves(x, LEAF)
    keep = few_copies(x, k + 1)
    others = [g[keep[g]] for g in groups]
    others = [g for g in others if len(g)]
    low, high = (np.array([f(x[g], axis=0) for g in others]).reshape(len(others), -1) for f in (np.min, np.max))
    z, norm, eps = middle(x)
    dims, z = x.shape[1], np.multiply(z, -2, out=z)
    b = np.column_stack([z, np.ones(len(x)), norm])
    del z
    for own in groups[part::parts]:
        mine = x[own]
        a = np.column_stack([b[own, :dims] / -2, norm[own], np.ones(len(own))])
        gap = (np.maximum(0, np.maximum(low - mine.max(axis=0), mine.min(axis=0) - high)) ** 2).sum(axis=1)
        turn = np.argsort(gap, kind="stable")
        end = np.full(len(own), np.inf)
        first = others[turn[0]]
        if len(first) > k:
            about = a @ b[first].T
            about[own[:, None] == first] = np.inf
            end = np.partition(about, k - 1, axis=1)[:, k - 1]
        vals, cols, at, step = np.empty((len(own), 0)), np.empty((len(own), 0), int), 0, 1
        held, fits = np.empty((len(own), WIDE)), np.empty((len(own), WIDE), bool)
        while at < len(turn) and gap[turn[at]] <= end.max() + eps:
            now = turn[at : at + step]
            at, step = at + step, 2 * step
            at_ = np.concatenate([others[g] for g in now[gap[now] <= end.max() + eps]])
            found = [(np.repeat(np.arange(len(own)), vals.shape[1]), cols.ravel(), vals.ravel())]
            for i in range(0, len(at_), WIDE):
                some = at_[i : i + WIDE]
                wide = len(some) == WIDE
                about = np.matmul(a, b[some].T, out=held if wide else None)
                at_most = np.less_equal(about, (end + eps)[:, None], out=fits if wide else None)
                row, col = np.divmod(np.flatnonzero(at_most), len(some))
                other = some[col] != own[row]
                row, col = row[other], col[other]
                found.append((row, some[col], about[row, col]))
            row, col, val = (np.concatenate(f) for f in zip(*found, strict=True))
            within = np.flatnonzero(val <= end[row] + eps)
            within = within[np.argsort(row[within], kind="stable")]
            row, col, val = row[within], col[within], val[within]
            count = np.bincount(row, minlength=len(own))
            place = np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)
            vals, cols = np.full((len(own), count.max(initial=0)), np.inf), np.zeros((len(own), count.max(initial=0)), int)
            vals[row, place], cols[row, place] = val, col
            if vals.shape[1] >= k:
                end = np.minimum(end, np.partition(vals, k - 1, axis=1)[:, k - 1])
        row, place = np.nonzero(vals <= np.where(np.isfinite(end), end + eps, np.finfo(float).max)[:, None])
        exact = np.full(vals.shape, np.inf)
        for i in range(0, len(row), 1 << 16):
            r_, p_ = row[i : i + (1 << 16)], place[i : i + (1 << 16)]
            exact[r_, p_] = far(x[cols[r_, p_]], mine[r_])
        exact.sort(axis=1)
        none = np.full(len(own), np.inf)
        yield own, exact[:, k - 1] if exact.shape[1] >= k else none, exact[:, 0] if exact.shape[1] else none


def run(x: np.ndarray, ids: np.ndarray, own: int, k: int, r: np.ndarray, near: np.ndarray, rules=RULES) -> Outcome:
    """Decisions for the vector at `own` as the query; all arrays follow the visiting order, witness is a position in x.

    Candidates are taken by blocks of the visiting order. Within a block one after the other settles, then the block's
    witnesses settle what is open behind it; the first witness that does counts. A pair is settled where the witness is
    nearer than c - d (accepted) or d - c (rejected), which is one product for all pairs of a block; pairs it finds are
    checked on their own. `near` tells witnesses that can't settle anything."""
    d = far(x, x[own])
    other = np.delete(d, own)
    r_q = np.partition(other, k - 1)[k - 1] if len(other) >= k else np.inf
    order = visit_order(d, ids, r_q)
    order = order[order != own]
    d, r, near = d[order], r[order], near[order]
    n = len(order)
    member = d <= r
    c = np.where(member, r * (1 - 1e-12), r * (1 + 1e-12))
    short = np.minimum(c, 4 * d.max(initial=0.0))  # it is infinite where there are fewer than k others
    z, norm, eps = middle(x)
    norm, eps, dims = norm[order], eps + ROOM * float(np.square(short).max(initial=0.0)), x.shape[1]
    columns = np.empty((n, dims + 3))
    np.take(np.multiply(z, -2, out=z), order, axis=0, out=columns[:, :dims])
    columns[:, dims], columns[:, dims + 1], columns[:, dims + 2] = 2 * d, 1, norm - d**2
    del z
    rule, witness = np.full(n, "knn", object), np.full(n, -1)
    decided = member.copy()
    open_ = np.ones(n, bool)
    if "semi" in rules:
        semi = d <= r_q / 2 * (1 - 1e-12)
        open_[semi], rule[semi], decided[semi] = False, "semi", True
    some = near * (1 - 1e-9)
    lowest, highest = (d[open_].min(), d[open_].max()) if open_.any() else (0.0, 0.0)
    strong = np.where(member, ("positive" in rules) & (lowest + some <= c * (1 + 1e-9)), ("negative" in rules) & (highest - some >= c * (1 - 1e-9)))
    strong &= ~member | np.isfinite(near)
    outer = int((d <= r_q).sum())  # these come first, from far to near; from here on d grows

    def settle(w: np.ndarray, left: np.ndarray) -> np.ndarray:
        """Of the pairs, which the first rule that fits settles."""
        dw = far(x[order[left]], x[order[w]])
        return np.where(member[w], d[left] + dw <= c[w], d[left] - dw > c[w])

    def rows(w: np.ndarray) -> np.ndarray:
        return np.column_stack([columns[w, :dims] / -2, short[w], norm[w] - short[w] ** 2, np.ones(len(w))])

    def mark(left: np.ndarray, w) -> None:
        open_[left], witness[left], decided[left] = False, w, member[w]
        rule[left] = np.where(member[w], "positive", "negative")

    rest, size = np.flatnonzero(open_), FIRST
    while len(rest):
        now, rest = rest[:size], rest[size:]
        able = np.flatnonzero(strong[now])
        if len(able):
            hit = rows(now[able]) @ columns[now].T <= eps
            for i, row in zip(able, hit, strict=True):
                if open_[now[i]]:
                    at = now[i + 1 :][row[i + 1 :]]
                    at = at[open_[at]]
                    if len(at):
                        at = at[settle(np.full(len(at), now[i]), at)]
                        mark(at, now[i])
            w = now[able][open_[now[able]]]
            for i in range(0, len(w), PIECE):
                wit = w[i : i + PIECE]
                # a rejected witness settles nothing nearer than c + near
                start = 0
                if not member[wit].any() and len(rest) and rest[0] >= outer:
                    start = int(np.searchsorted(d[rest], (c[wit] + some[wit]).min() * (1 - 1e-9)))
                a = rows(wit)
                behind = rest[start:]
                behind = behind[open_[behind]]
                for j in range(0, len(behind), WIDE):
                    left = behind[j : j + WIDE]
                    hit = a @ columns[left].T <= eps
                    todo = np.flatnonzero(hit.any(axis=0))
                    while len(todo):
                        by = hit[:, todo].argmax(axis=0)
                        sure = settle(wit[by], left[todo])
                        mark(left[todo[sure]], wit[by[sure]])
                        hit[by[~sure], todo[~sure]] = False
                        todo = todo[~sure]
                        todo = todo[hit[:, todo].any(axis=0)]
            rest = rest[open_[rest]]
        size = min(2 * size, BLOCK)
    return Outcome(decided, rule, np.where(witness < 0, -1, order[witness]), np.where(rule == "knn", r, np.nan), order)
