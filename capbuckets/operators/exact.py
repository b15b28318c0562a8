"""The exact many-size optimum, for few values: a linear program over the numbers of buckets, cuts, and branching.

Rows can be dealt into b_S buckets of each size S if and only if for every set A of values

    rows(A) <= sum over S of min(sum of A's quotas in a bucket of S, S) * b_S

(the smallest cut of the flow from values to sizes). These inequalities are added where a maximum flow finds them
violated; branching makes the b_S whole. The search stops after a number of nodes, never by the clock, so its answers are
the same on every machine.
"""

from __future__ import annotations

import heapq
from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np

EPS = 1e-7
#: Nodes that a search looks at before it gives the best so far.
MAX_NODES = 300


@dataclass
class Exact:
    """``layout`` and ``loss`` of the best layout found; ``bound``: no layout has less; optimal if they meet.

    ``stopped`` says why the search ended before that: ``nodes`` or ``simplex``.
    """

    layout: list[tuple[int, int]]
    loss: int | None
    bound: float
    nodes: int = 0
    stopped: str = ""

    @property
    def optimal(self) -> bool:
        return self.loss is not None and bool(np.ceil(self.bound - 1e-6) >= self.loss)


class SimplexStopped(ArithmeticError):
    """The simplex method ran out of steps: what it holds is no bound."""


def max_flow(supply: np.ndarray, middle: np.ndarray, demand: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """(value, flow by value and class, values on the source side of a smallest cut)."""
    m, q = middle.shape
    flow = np.zeros((m, q), middle.dtype)
    left, room = supply.copy(), demand.copy()
    for i in range(m):  # greedy start
        for j in range(q):
            x = min(left[i], middle[i, j], room[j])
            flow[i, j], left[i], room[j] = x, left[i] - x, room[j] - x
    tiny = 0 if np.issubdtype(middle.dtype, np.integer) else 1e-9
    while True:
        # breadth first from values with supply left; parents tell the way back
        from_class = np.full(m, -2)
        from_value = np.full(q, -1)
        frontier = [i for i in range(m) if left[i] > tiny]
        from_class[frontier] = -1
        end = -1
        while frontier and end < 0:
            reached = []
            for i in frontier:
                for j in np.flatnonzero((from_value < 0) & (middle[i] - flow[i] > tiny)):
                    from_value[j] = i
                    if room[j] > tiny:
                        end = int(j)
                        break
                    for k in np.flatnonzero((from_class == -2) & (flow[:, j] > tiny)):
                        from_class[k] = j
                        reached.append(int(k))
                if end >= 0:
                    break
            frontier = reached
        if end < 0:
            return float(flow.sum()), flow, from_class > -2
        path, j = [], end
        while True:
            i = int(from_value[j])
            path.append((i, j, 1))
            if from_class[i] == -1:
                break
            j = int(from_class[i])
            path.append((i, j, -1))
        x = min([left[i], room[end], *[middle[a, b] - flow[a, b] if s > 0 else flow[a, b] for a, b, s in path]])
        for a, b, s in path:
            flow[a, b] += s * x
        left[i] -= x
        room[end] -= x


def flow_split(counts: Sequence[int], quotas: Sequence[Sequence[int]], layout: Sequence[tuple[int, int]]) -> list[list[int]] | None:
    """Rows of each value in each class of any layout, or None if the layout is not valid. ``quotas[v][j]``: in one bucket."""
    b = np.array([x for _, x in layout], np.int64)
    o = np.asarray(counts, np.int64)
    value, flow, _ = max_flow(o.copy(), np.asarray(quotas, np.int64) * b, np.array([s * x for s, x in layout], np.int64))
    full = int(value) == int(o.sum()) == sum(s * x for s, x in layout)
    return flow.tolist() if full else None


def simplex(cost: np.ndarray, a: np.ndarray, rhs: np.ndarray, equal: np.ndarray, steps: int = 5000) -> tuple[float, np.ndarray] | None:
    """min cost x over a x >= rhs (= where ``equal``), x >= 0; None if there is no x. Two phases, smallest index on ties.

    Raises :class:`SimplexStopped` if a phase does not end within ``steps``, or the cost has no least value.
    """
    m, n = a.shape
    sign = np.where(rhs < 0, -1.0, 1.0)
    slack = np.diag(np.where(equal, 0.0, -1.0))[:, ~equal]
    t = np.hstack([sign[:, None] * np.hstack([a, slack]), np.eye(m), (sign * rhs)[:, None]])
    width, basis = n + slack.shape[1], list(range(n + slack.shape[1], n + slack.shape[1] + m))
    for phase in (1, 2):
        c = np.zeros(width + m)
        if phase == 1:
            c[width:] = 1
        else:
            c[:n] = cost
            c[width:] = 1e6 * max(1.0, float(np.abs(cost).max()))  # those still in the basis must stay at nought
        usable = width + m if phase == 1 else width
        for _ in range(steps):
            reduced = c[:usable] - c[basis] @ t[:, :usable]
            enter = int(reduced.argmin()) if _ < 500 else next((int(j) for j in np.flatnonzero(reduced < -EPS)), 0)
            if reduced[enter] >= -EPS:
                break
            column = t[:, enter]
            ratio = np.where(column > EPS, t[:, -1] / np.where(column > EPS, column, 1), np.inf)
            row = int(ratio.argmin())
            if not np.isfinite(ratio[row]):
                raise SimplexStopped("the cost has no least value")
            t[row] /= t[row, enter]
            others = np.arange(m) != row
            t[others] -= np.outer(t[others, enter], t[row])
            basis[row] = enter
        else:
            raise SimplexStopped(f"no end within {steps} steps")
        if phase == 1 and float(c[basis] @ t[:, -1]) > 1e-5 * max(1.0, float(np.abs(rhs).max(initial=0))):
            return None
    x = np.zeros(width + m)
    x[basis] = t[:, -1]
    return float(cost @ x[:n]), x[:n]


def _relaxed(o, quotas, sizes, n, cuts, extra) -> tuple[float, np.ndarray] | None:
    """The linear bound under extra bounds on single variables; new cuts are added to ``cuts``."""
    cost = (sizes - 1.0) ** 2
    while True:
        rows = [sizes.astype(float), *[c for c, _ in cuts], *[s * np.eye(len(sizes))[j] for j, s, _ in extra]]
        rhs = np.array([float(n), *[r for _, r in cuts], *[s * x for _, s, x in extra]])
        scale = np.array([max(1.0, np.abs(r).max()) for r in rows])
        solved = simplex(cost, np.array(rows) / scale[:, None], rhs / scale, np.array([True] + [False] * (len(rows) - 1)))
        if solved is None:
            return None
        value, b = solved
        flow, _, side = max_flow(o.astype(float), quotas * b, sizes * b)
        if flow >= n - 1e-5 * max(1, n**0.5):
            return value, b
        cut = np.minimum(quotas[side].sum(0), sizes).astype(float)
        if float(cut @ b) >= float(o[side].sum()) - 1e-6 * max(1, n):
            return value, b
        cuts.append((cut, float(o[side].sum())))


def lp_bound(counts: Sequence[int], quotas: np.ndarray, sizes: Sequence[int]) -> float | None:
    """A lower bound on the loss of every layout of the given sizes; None if there is none. ``quotas[v][j]``: of size j."""
    o = np.asarray(counts, np.int64)
    got = _relaxed(o, np.asarray(quotas), np.asarray(sizes), int(o.sum()), _first_cuts(o, np.asarray(quotas), np.asarray(sizes)), [])
    return None if got is None else got[0]


def _first_cuts(o, quotas, sizes) -> list:
    return [(np.minimum(q, sizes).astype(float), float(x)) for q, x in zip(quotas, o, strict=True)]


def _dive(o, quotas, sizes, n, cuts, b, most: int = 80) -> np.ndarray | None:
    """A whole solution on a way down from ``b``: the variable nearest to a whole number is held there, or beside it, in turn."""
    extra: list = []
    for _ in range(most):
        part = np.abs(b - np.round(b))
        if part.max() < 1e-6:
            whole = np.round(b).astype(np.int64)
            flow, _, _ = max_flow(o.copy(), quotas * whole, sizes * whole)
            return whole if int(flow) == n == int(sizes @ whole) else None
        for j in [int(k) for k in np.argsort(part) if part[k] >= 1e-6]:
            near = float(np.round(b[j]))
            tried = [[*extra, (j, 1.0, x), (j, -1.0, x)] for x in (near, near + (1.0 if b[j] > near else -1.0))]
            found = next(((more, got[1]) for more in tried if (got := _relaxed(o, quotas, sizes, n, cuts, more)) is not None), None)
            if found:
                extra, b = found
                break
        else:
            return None
    return None


def exact_multi(counts: Sequence[int], num: Sequence[int], den: Sequence[int], m_max: int = 50, start: tuple[list[tuple[int, int]], int] | None = None, max_nodes: int = MAX_NODES) -> Exact:
    """The least-loss layout of any number of sizes, or the best one found and a bound after ``max_nodes`` nodes.

    ``start``: a layout known to be valid, and its loss.
    """
    o = np.asarray(counts, np.int64)
    n = int(o.sum())
    low = min(-(-int(b) // int(a)) for a, b in zip(num, den, strict=True))
    sizes = np.arange(low, m_max + 1)
    quotas = np.array([[min(int(s), int(s) * int(a) // int(b)) for s in sizes] for a, b in zip(num, den, strict=True)], np.int64)
    best = Exact([] if start is None else start[0], None if start is None else start[1], 0.0)
    cuts = _first_cuts(o, quotas, sizes)
    try:
        root = _relaxed(o, quotas, sizes, n, cuts, [])
    except SimplexStopped:
        best.stopped = "simplex"
        return best
    if root is None:
        return Exact([], None, float("inf"))
    heap, tick = [(root[0], 0, root[1], ())], 0
    try:
        whole = _dive(o, quotas, sizes, n, cuts, root[1])
    except SimplexStopped:
        whole = None
    if whole is not None and (best.loss is None or int(whole @ (sizes - 1) ** 2) < best.loss):
        best.layout, best.loss = [(int(s), int(x)) for s, x in zip(sizes, whole, strict=True) if x], int(whole @ (sizes - 1) ** 2)
    while heap:
        bound, _, b, extra = heapq.heappop(heap)
        best.bound = bound
        if best.loss is not None and np.ceil(bound - 1e-6) >= best.loss:
            best.bound = float(best.loss)
            return best
        if best.nodes >= max_nodes:
            best.stopped = "nodes"
            return best
        best.nodes += 1
        part = np.abs(b - np.round(b))
        j = int(part.argmax())
        branches = [(*extra, (j, -1.0, float(np.floor(b[j])))), (*extra, (j, 1.0, float(np.ceil(b[j]))))]
        if part[j] < 1e-6:
            whole = np.round(b).astype(np.int64)
            flow, _, side = max_flow(o.copy(), quotas * whole, sizes * whole)
            if int(flow) == n == int(sizes @ whole):
                loss = int(whole @ (sizes - 1) ** 2)
                if best.loss is None or loss < best.loss:
                    best.layout, best.loss = [(int(s), int(x)) for s, x in zip(sizes, whole, strict=True) if x], loss
                continue
            # whole but not dealable: the cut that forbids it, or, within the tolerance of the flow, other whole numbers
            cut = np.minimum(quotas[side].sum(0), sizes).astype(float)
            if float(cut @ whole) < float(o[side].sum()):
                cuts.append((cut, float(o[side].sum())))
                branches = [extra]
            else:
                branches = [(*extra, (k, s, float(whole[k] + s))) for k in range(len(sizes)) for s in (-1.0, 1.0) if whole[k] + s >= 0]
        for more in branches:
            try:
                got = _relaxed(o, quotas, sizes, n, cuts, list(more))
            except SimplexStopped:
                best.stopped = "simplex"
                return best
            if got is not None and (best.loss is None or np.ceil(got[0] - 1e-6) < best.loss):
                tick += 1
                heapq.heappush(heap, (got[0], tick, got[1], more))
    best.bound = float(best.loss) if best.loss is not None else float("inf")
    return best


def exact_enumerate(counts: Sequence[int], num: Sequence[int], den: Sequence[int], m_max: int = 50) -> tuple[list[tuple[int, int]], int] | None:
    """The optimum by trying every layout in order of sizes; for some dozen rows."""
    n = sum(counts)
    low = min(-(-int(b) // int(a)) for a, b in zip(num, den, strict=True))
    best: list = [None, None]

    def walk(size: int, left: int, loss: int, layout: list) -> None:
        if best[1] is not None and loss >= best[1]:
            return
        if not left:
            quotas = [[min(s, s * int(a) // int(b)) for s, _ in layout] for a, b in zip(num, den, strict=True)]
            if flow_split(counts, quotas, layout) is not None:
                best[:] = [list(layout), loss]
            return
        if size > min(m_max, left):
            return
        for b in range(left // size, -1, -1):
            walk(size + 1, left - b * size, loss + b * (size - 1) ** 2, [*layout, (size, b)] if b else layout)

    walk(low, n, 0, [])
    return None if best[1] is None else (best[0], best[1])
