"""The verification cascade of one query, on arrays.

Candidates are visited in a given order. Each is settled by the first rule that applies: half-radius circle of the
query; ellipse or hyperbola of a witness reached through visited neighbours (or any witness); else its own kNN radius
is computed from the bundle, and it becomes a witness. Rules save work only, so the answer doesn't depend on order,
matching or the neighbour graph; what does is how many witnesses are needed."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from revnn.functions.geometry import MARGIN

RULES = ("semi", "positive", "negative")
ORDERS = ("boundary_out", "asc", "desc", "hash", "boundary")


@dataclass
class Outcome:
    """For each candidate: member, rule that settled it, witness used (position, -1 for none), own radius (nan)."""

    member: np.ndarray
    rule: np.ndarray
    witness: np.ndarray
    radius: np.ndarray
    order: np.ndarray
    tested: int = 0
    extra: dict = field(default_factory=dict)

    @property
    def n_witnesses(self) -> int:
        return int((self.rule == "knn").sum())


def visit_order(d: np.ndarray, ids: np.ndarray, r_q: float, order: str = "boundary_out") -> np.ndarray:
    """boundary_out: those within the kNN circle from far to near, then the others from near to far."""
    up = np.lexsort((ids, d))
    if order == "boundary_out":
        inner = d[up] <= r_q
        return np.concatenate([up[inner][::-1], up[~inner]])
    if order == "asc":
        return up
    if order == "desc":
        return up[::-1]
    if order == "boundary":
        return np.lexsort((ids, np.abs(d - r_q)))
    return np.argsort((ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(16), kind="stable")


def knn_radius2(points: np.ndarray, ids: np.ndarray, at: np.ndarray, own: int, k: int) -> float:
    """Squared distance from `at` to the k-th of the other points."""
    dx, dy = points[:, 0] - at[0], points[:, 1] - at[1]
    d2 = (dx * dx + dy * dy)[ids != own]
    return float(np.partition(d2, k - 1)[k - 1]) if len(d2) >= k else np.inf


def run(q, q_id, k: int, cand: np.ndarray, cand_ids: np.ndarray, points: np.ndarray, ids: np.ndarray, r_q: float, reach: float = np.inf, order: str = "boundary_out", match: str = "exhaustive", rules=RULES, neighbours=None) -> Outcome:
    """cand (n, 2) and points (m, 2) with ids; points hold every point within `reach` of the query.

    A candidate farther than half of `reach` gets no radius here; what no conic settles of these has rule 'deferred'.

    neighbours: for each candidate the positions of its graph neighbours among the candidates, for match='graph'."""
    n = len(cand)
    dx, dy = cand[:, 0] - q[0], cand[:, 1] - q[1]
    d2 = dx * dx + dy * dy
    d = np.sqrt(d2)
    out = Outcome(np.zeros(n, bool), np.full(n, "", object), np.full(n, -1), np.full(n, np.nan), visit_order(d, cand_ids, r_q, order))
    visited, link = np.zeros(n, bool), np.full(n, -1)
    w_at, w_r, w_member, w_d = np.zeros(n, int), np.zeros(n), np.zeros(n, bool), np.zeros(n)
    count = 0
    slot, late = np.full(n, -1), []
    for i in out.order:
        visited[i] = True
        if d2[i] == 0 or "semi" in rules and d[i] <= r_q / 2 * (1 - MARGIN):
            out.member[i], out.rule[i] = True, "semi"
            continue
        if match == "exhaustive":
            tried = np.arange(count)
        else:
            near = [j if out.rule[j] == "knn" else link[j] for j in neighbours[i] if visited[j]]
            tried = np.array(sorted({slot[j] for j in near if j >= 0}), int)
        if len(tried):
            out.tested += len(tried)
            at = cand[w_at[tried]]
            dw = np.sqrt((cand[i, 0] - at[:, 0]) ** 2 + (cand[i, 1] - at[:, 1]) ** 2)
            r = w_r[tried]
            yes = w_member[tried] & (d[i] + dw <= r * (1 - MARGIN)) if "positive" in rules else np.zeros(len(tried), bool)
            no = ~w_member[tried] & (d[i] - dw > r * (1 + MARGIN)) if "negative" in rules else np.zeros(len(tried), bool)
            hit = np.flatnonzero(yes | no)
            if len(hit):
                link[i] = w_at[tried[hit[0]]]
                out.member[i], out.rule[i], out.witness[i] = yes[hit[0]], "positive" if yes[hit[0]] else "negative", link[i]
                continue
        if 2 * d[i] > reach * (1 + MARGIN):  # its circle sticks out of the bundle: no radius from here
            late.append(i)
            continue
        r2 = knn_radius2(points, ids, cand[i], cand_ids[i], k)
        out.member[i], out.rule[i], out.radius[i] = d2[i] <= r2, "knn", np.sqrt(r2)
        # an accepted witness's circle may leave the bundle: a smaller radius is as sound for the ellipse
        r = min(np.sqrt(r2), reach - d[i]) if out.member[i] else np.sqrt(r2)
        w_at[count], w_r[count], w_member[count], w_d[count], slot[i] = i, r, out.member[i], d[i], count
        count += 1
    # later witnesses may settle what was deferred
    for i in late:
        dw = np.sqrt(((cand[w_at[:count]] - cand[i]) ** 2).sum(axis=1))
        out.tested += count
        yes = w_member[:count] & (d[i] + dw <= w_r[:count] * (1 - MARGIN)) & ("positive" in rules)
        no = ~w_member[:count] & (d[i] - dw > w_r[:count] * (1 + MARGIN)) & ("negative" in rules)
        hit = np.flatnonzero(yes | no)
        out.rule[i] = "deferred"
        if len(hit):
            out.member[i], out.rule[i], out.witness[i] = yes[hit[0]], "positive" if yes[hit[0]] else "negative", w_at[hit[0]]
    return out


def decided_by(d: np.ndarray, cand: np.ndarray, w: int, r: float) -> np.ndarray:
    """Which candidates a witness with radius r settles (either rule)."""
    dw = np.sqrt(((cand - cand[w]) ** 2).sum(axis=1))
    return (d + dw <= r * (1 - MARGIN)) if d[w] <= r else (d - dw > r * (1 + MARGIN))


def greedy_cover(settles: np.ndarray) -> list[int]:
    """Witnesses by largest gain until every candidate is settled or a witness; settles[w, c]."""
    left, chosen = np.ones(len(settles), bool), []
    settles = settles | np.eye(len(settles), dtype=bool)
    while left.any():
        w = int((settles & left).sum(axis=1).argmax())
        chosen.append(w)
        left &= ~settles[w]
    return chosen


def minimum_cover(settles: np.ndarray, most: int = 12) -> list[int]:
    """The smallest witness set, by trying sets in order of size; for at most `most` candidates."""
    from itertools import combinations

    n = len(settles)
    if n > most:
        raise ValueError(f"an exact minimum is only searched for up to {most} candidates")
    settles = settles | np.eye(n, dtype=bool)
    for size in range(n + 1):
        for some in combinations(range(n), size):
            if settles[list(some)].any(axis=0).all() if some else n == 0:
                return list(some)
    return list(range(n))
