"""Layouts of many sizes: repeated two-size refinement of parts.

A part is a vector of counts and the class of equal buckets that holds it. Only counts matter for decisions, so the
work list lives on the driver and rows are moved once, when the leaves are known.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

import numpy as np

from capbuckets.operators.assign import Cut, cut_points, split_counts
from capbuckets.operators.search import Counts, driver_search


@dataclass
class Refinement:
    """Leaves as (size, buckets, counts by value); ``loss`` is their sum."""

    leaves: list[tuple[int, int, np.ndarray]] = field(default_factory=list)
    loss: int | None = None
    reason: str = ""
    searches: int = 0


def refine(counts: Sequence[int], num: Sequence[int], den: Sequence[int], m_max: int = 50, order: str = "rare_first") -> Refinement:
    """Splits the single bucket of all rows, and then each part, as long as a two-size layout of the part has less loss.

    Caps stay those of the whole table. Absent values drop out of a part. Every split lowers the loss, so it ends.
    """
    o, num, den = (np.asarray(x, object) for x in (counts, num, den))
    n = int(sum(counts))
    out = Refinement()
    if not n or any(int(c) * int(b) > int(a) * n for c, a, b in zip(o, num, den, strict=True)):
        out.reason = "a value is more frequent than its cap" if n else "no rows"
        return out
    work = [(np.asarray(counts, np.int64), n, 1)]
    num64, den64 = np.asarray(num, np.int64), np.asarray(den, np.int64)
    while work:
        part, size, buckets = work.pop()
        own = part > 0
        c = Counts(part[own], num64[own], den64[own], np.ones(int(own.sum()), np.int64))
        out.searches += 1
        found = driver_search(c, m_max)
        if found.loss is not None and found.loss < buckets * (size - 1) ** 2:
            (s1, b1), (s2, b2) = found.classes
            halves = np.array(split_counts(c.cnt, c.quota(s1), c.quota(s2), found.classes, order))
            for j, (s, b) in enumerate(found.classes):
                if b:
                    new = np.zeros_like(part)
                    new[own] = halves[:, j]
                    work.append((new, s, b))
        else:
            out.leaves.append((size, buckets, part))
    out.leaves.sort(key=lambda x: (x[0], x[1], x[2].tolist()))
    out.loss = sum(b * (s - 1) ** 2 for s, b, _ in out.leaves)
    return out


def layout_of(r: Refinement) -> list[tuple[int, int]]:
    """Classes of the leaves, equal sizes merged."""
    total: dict[int, int] = {}
    for s, b, _ in r.leaves:
        total[s] = total.get(s, 0) + b
    return sorted(total.items())


def leaf_cuts(r: Refinement, values: Sequence) -> list[Cut]:
    """Cut points that deal rows into the leaves."""
    takes = [[int(part[i]) for _, _, part in r.leaves] for i in range(len(values))]
    return cut_points(values, takes, [(s, b) for s, b, _ in r.leaves])


def refine_caps(rows: Sequence, m_max: int = 50, order: str = "rare_first") -> Refinement:
    """:func:`refine` on collected caps."""
    return refine([r.cnt for r in rows], [r.cap_num for r in rows], [r.cap_den for r in rows], m_max, order)
