"""The plane as a line: leaves of a tree over a space-filling curve, refined where the answers say it could be dense.

A leaf is named by its first key at the finest level, so refining one never renames another. Its size grows with the
number of calls, so it lives on the driver.
"""

from __future__ import annotations

import bisect
import math
import random

import numpy as np

from knnscope.functions import curves
from knnscope.operators.service import Answer, crawl_box

#: exact crawls a smallest leaf that an answer leaves open, at the price of more calls.
LEAF_TESTS = ("in_cell", "circumscribed", "inscribed", "exact")


class CurveTree:
    """Leaves over the square ``domain = (x0, y0, side)``.

    ``fanout`` children per split; ``min_side`` is the smallest leaf; ``adaptive=False`` starts with all leaves of that
    side and never splits. A leaf is split if at least ``split_threshold`` points may lie in it: if that many are within
    half its diagonal of its centre.
    """

    def __init__(
        self, domain, min_side: float, min_pts: int, kind: str = "hilbert", fanout: int | None = None, adaptive: bool = True,
        init_level: int = 1, split_threshold: int | None = None, leaf_test: str = "in_cell", infer: bool = True,
        seed_policy: str = "leaf", prior=None, service=None,
    ):
        if leaf_test == "exact" and service is None:
            raise ValueError("the exact leaf test needs the service")
        self.service = service
        self.domain, self.kind, self.min_pts, self.infer = domain, kind, min_pts, infer
        b = curves.base(kind)
        self.fanout = fanout or b * b
        step = round(math.log(self.fanout, b * b))
        if (b * b) ** step != self.fanout:
            raise ValueError(f"children per node must be a power of {b * b}")
        if leaf_test not in LEAF_TESTS:
            raise ValueError(f"leaf_test must be one of {LEAF_TESTS}")
        levels = math.log(domain[2] / min_side, b)
        if abs(levels - round(levels)) > 1e-6:
            raise ValueError(f"min_side must be the domain's side over a power of {b}")
        self.levels, self.step = round(levels), step
        self.split_threshold = split_threshold or min_pts
        self.leaf_test, self.seed_policy, self.prior = leaf_test, seed_policy, prior
        self.version = self.contradictions = 0
        first = self.levels if not adaptive else min(self.levels, max(1, init_level) * step)
        self.width = (b * b) ** self.levels  # keys on the whole line
        self.keys: list[int] = []
        self.boxes: dict[int, tuple[float, float, float]] = {}  # first key -> centre and side
        self.level: dict[int, int] = {}
        self.state: dict[int, bool] = {}
        self.sparse: list[int] = []
        self.internal = 0
        self._add(range((b * b) ** first), first)
        self._arrays = None

    def _add(self, prefixes, level: int) -> None:
        b = curves.base(self.kind)
        span, side = (b * b) ** (self.levels - level), self.domain[2] / b**level
        prefixes = np.array(list(prefixes), np.int64)
        cx, cy = curves.cells(self.kind, prefixes, level)
        for p, x, y in zip(prefixes.tolist(), cx.tolist(), cy.tolist()):
            key = p * span
            self.boxes[key] = (self.domain[0] + (x + 0.5) * side, self.domain[1] + (y + 0.5) * side, side)
            self.level[key] = level
            bisect.insort(self.keys, key)
        self._arrays = None

    # --- the line
    def size(self) -> int:
        return len(self.keys)

    def at(self, rank: int) -> int:
        return self.keys[rank]

    def rank(self, key: int) -> int:
        """The place of the leaf that holds a key."""
        return bisect.bisect_right(self.keys, key) - 1

    def current(self, key: int) -> int:
        return self.keys[self.rank(key)]

    def place(self, key: int) -> tuple[float, float]:
        return self.boxes[key][:2]

    def known(self, key: int) -> bool | None:
        return self.state.get(key)

    def last_key(self, key: int) -> int:
        return key + (curves.base(self.kind) ** 2) ** (self.levels - self.level[key]) - 1

    def locate(self, xs, ys) -> np.ndarray:
        """Keys of places; -1 outside the domain."""
        n = curves.base(self.kind) ** self.levels
        cx = np.floor((np.asarray(xs, float) - self.domain[0]) / (self.domain[2] / n)).astype(np.int64)
        cy = np.floor((np.asarray(ys, float) - self.domain[1]) / (self.domain[2] / n)).astype(np.int64)
        ok = (cx >= 0) & (cx < n) & (cy >= 0) & (cy < n)
        found = np.full(len(cx), -1, np.int64)
        if ok.any():
            found[ok] = curves.keys(self.kind, cx[ok], cy[ok], self.levels)
        return found

    def mark(self, key: int, dense: bool) -> None:
        old = self.state.get(key)
        if old is None:
            self.state[key] = dense
            if not dense:
                bisect.insort(self.sparse, key)
        elif old != dense:
            self.contradictions += 1

    def learn(self, key: int, answer: Answer) -> str:
        """Split the leaf that was asked, or set its state; then set what the certified ball tells of other leaves."""
        x, y, side = self.boxes[key]
        may = answer.reach(self.split_threshold) <= side * 2**0.5 / 2
        node = "leaf"
        if self.level[key] < self.levels and may:
            self._split(key)
            node = "split"
        elif self.level[key] < self.levels:
            self.mark(key, False)
        else:
            if self.leaf_test in ("in_cell", "exact"):
                half = side / 2
                inside = lambda xs, ys, w=1: int((((xs >= x - half) & (xs < x + half) & (ys >= y - half) & (ys < y + half)) * w).sum())
                n = inside(answer.xs, answer.ys, answer.weights)
                if self.leaf_test == "exact" and n < self.min_pts and answer.radius <= side / 2**0.5:
                    found = np.array(list(crawl_box(self.service, (x - half, y - half, x + half, y + half), "leaf").values())).reshape(-1, 2)
                    n = inside(found[:, 0], found[:, 1])
                dense = n >= self.min_pts
            else:
                reach = side / 2 * (2**0.5 if self.leaf_test == "circumscribed" else 1)
                dense = answer.reach(self.min_pts) <= reach
            self.mark(key, dense)
        if self.infer:
            self._infer(answer)
        return node

    def _split(self, key: int) -> None:
        level = min(self.levels, self.level[key] + self.step)
        parts = (curves.base(self.kind) ** 2) ** (level - self.level[key])
        span = (curves.base(self.kind) ** 2) ** (self.levels - level)
        self.keys.pop(self.rank(key))
        del self.boxes[key], self.level[key]
        self._add(range(key // span, key // span + parts), level)
        self.internal += 1
        self.version += 1

    def _leaves(self):
        if self._arrays is None:
            self._arrays = np.array(self.keys), np.array([self.boxes[k] for k in self.keys])
        return self._arrays

    def _infer(self, answer: Answer) -> None:
        """Leaves wholly inside the certified ball have exactly the points that the answer holds."""
        keys, box = self._leaves()
        half = box[:, 2] / 2
        far = np.hypot(np.abs(box[:, 0] - answer.x) + half, np.abs(box[:, 1] - answer.y) + half)
        inside = far < answer.radius
        if not inside.any():
            return
        own = self.locate(answer.xs, answer.ys)
        counts = np.bincount(np.searchsorted(keys, own[own >= 0], side="right") - 1, answer.weights[own >= 0], len(keys))
        for i in np.flatnonzero(inside).tolist():
            key, dense = int(keys[i]), bool(counts[i] >= self.min_pts)
            # a large leaf that holds enough points is still to be cut
            if key not in self.state and (not dense or self.level[key] == self.levels):
                self.mark(key, dense)

    def beyond(self, key: int, answer: Answer, toward: int) -> int | None:
        own = self.locate(answer.xs, answer.ys)
        r = self.rank(key)
        ranks = np.array([self.rank(k) for k in own[own >= 0].tolist()], np.int64)
        ranks = ranks[(ranks - r) * toward > 0]
        if not len(ranks):
            return None
        return self.keys[int(ranks.min() if toward > 0 else ranks.max())]

    def first_open(self, key: int, answer: Answer, toward: int) -> int | None:
        """The first leaf on that side whose state is unknown; a stretch of keys is no ball, so the states decide."""
        r = self.rank(key) + toward
        while 0 <= r < len(self.keys) and self.state.get(self.keys[r]) is False:
            r += toward
        return self.keys[r] if 0 <= r < len(self.keys) else None

    def nearest_sparse(self, key: int, toward: int) -> int | None:
        i = bisect.bisect_left(self.sparse, key)
        if toward > 0:
            return self.sparse[i] if i < len(self.sparse) else None
        return self.sparse[i - 1] if i else None

    def random_unknown(self, rng: random.Random) -> int | None:
        left = [k for k in self.keys if k not in self.state]
        if not left:
            return None
        if self.seed_policy == "leaf":
            return rng.choice(left)
        if self.seed_policy == "area":
            return rng.choices(left, [self.boxes[k][2] ** 2 for k in left])[0]
        weights = [self.prior(*self.boxes[k]) for k in left]  # external knowledge of where points are
        return rng.choices(left, weights)[0] if sum(weights) > 0 else rng.choice(left)

    def table(self) -> list[tuple]:
        """``level, lo_key, hi_key, x, y, side, state`` of every leaf."""
        return [
            (self.level[k], k, self.last_key(k), *self.boxes[k], {True: "dense", False: "sparse"}.get(self.state.get(k), "unknown"))
            for k in self.keys
        ]


def centres(domain, min_side: float, kind: str = "hilbert", adaptive: bool = True) -> list[tuple[float, float]]:
    """Where a tree may ask: the centres of its cells of every level, or of the smallest alone."""
    b, (x0, y0, whole) = curves.base(kind), domain
    levels = round(math.log(whole / min_side, b))
    found = []
    for level in range(1 if adaptive else levels, levels + 1):
        side = whole / b**level
        found += [(x0 + (i + 0.5) * side, y0 + (j + 0.5) * side) for i in range(b**level) for j in range(b**level)]
    return found


def smallest_cells(domain, min_side: float, kind: str = "hilbert") -> tuple[float, float, float]:
    """Corner and side of a tree's smallest cells, by which a service may count its answers."""
    b = curves.base(kind)
    return domain[0], domain[1], domain[2] / b ** round(math.log(domain[2] / min_side, b))


def weights_from_counts(counts: list[tuple[float, float, float]], reach: float):
    """A prior for ``seed_policy='prior'``: counts at places (population, housing units), summed over a leaf and round it."""
    c = np.array(counts, float).reshape(-1, 3)

    def weight(x: float, y: float, side: float) -> float:
        near = (np.abs(c[:, 0] - x) <= side / 2 + reach) & (np.abs(c[:, 1] - y) <= side / 2 + reach)
        return float(c[near, 2].sum())

    return weight
