"""Boundary pursuit: runs of dense cells on a line, found by few calls.

A line is a sequence of cells with a place to ask for each. ``GridLine`` has equal cells in one dimension; a curve tree's
leaves are a line too (``curvetree``). A search is a generator that yields the cells it wants to know and is resumed when
they are known, so that many searches share one round of calls.
"""

from __future__ import annotations

import bisect
import math
import random
from collections.abc import Generator, Iterable

from knnscope.operators.service import Answer, BudgetExhausted

#: walk asks cell after cell; skip follows returned points and leaps over what answers prove empty; bisect halves; auto skips
#: until noise stands in the way, and then halves.
STRATEGIES = ("walk", "skip", "bisect", "auto")


class GridLine:
    """``n`` half-open cells of width ``side`` from ``low`` on; a cell is named by its number."""

    def __init__(self, low: float, high: float, side: float, min_pts: int, rule: str = "min_pts", infer: bool = True):
        self.low, self.side, self.min_pts, self.rule, self.infer = low, side, min_pts, rule, infer
        self.n = max(1, math.ceil((high - low) / side - 1e-9))
        self.state: dict[int, bool] = {}
        self.sparse: list[int] = []
        self.version = 0
        self.contradictions = 0

    def place(self, cell: int) -> tuple[float, float]:
        return self.low + (cell + 0.5) * self.side, 0.0

    def cell_of(self, x: float, y: float = 0.0) -> int | None:
        c = math.floor((x - self.low) / self.side)
        return c if 0 <= c < self.n else None

    def places(self) -> list[tuple[float, float]]:
        return [self.place(c) for c in range(self.n)]

    def rank(self, cell: int) -> int:
        return cell

    def at(self, rank: int) -> int:
        return rank

    def size(self) -> int:
        return self.n

    def mark(self, cell: int, dense: bool) -> None:
        old = self.state.get(cell)
        if old is None:
            self.state[cell] = dense
            if not dense:
                bisect.insort(self.sparse, cell)
        elif old != dense:
            self.contradictions += 1

    def learn(self, cell: int, answer: Answer) -> str:
        """The cell's state from the call at its centre; and, free of charge, those of cells inside the certified ball."""
        inside = [self.cell_of(x) for x in answer.xs.tolist()]
        if self.rule == "all_k" or answer.weight is not None:
            if self.rule != "all_k" and answer.n > self.min_pts:
                raise ValueError("counted answers have no order: k must be min_pts")
            dense = answer.n >= self.min_pts and all(c == cell for c in inside)
        else:
            first = inside[: self.min_pts]
            dense = len(first) >= self.min_pts and all(c == cell for c in first)
        self.mark(cell, dense)
        if self.infer:
            for c, known in self.certified(answer, inside).items():
                if c != cell:
                    self.mark(c, known)
        return "leaf"

    def certified(self, answer: Answer, inside: list[int | None] | None = None) -> dict[int, bool]:
        if inside is None:
            inside = [self.cell_of(x) for x in answer.xs.tolist()]
        if not math.isfinite(answer.radius):
            lo, hi = 0, self.n - 1
            if self.n > 1_000_000:  # everything is known; only cells with points need to be named
                return {}
        else:
            lo = math.ceil((answer.x - answer.radius - self.low) / self.side + 1e-9)
            hi = math.floor((answer.x + answer.radius - self.low) / self.side - 1e-9) - 1
        counts: dict[int, int] = {}
        for c, n in zip(inside, answer.weights.tolist()):
            if c is not None:
                counts[c] = counts.get(c, 0) + n
        return {c: counts.get(c, 0) >= self.min_pts for c in range(max(0, lo), min(self.n - 1, hi) + 1)}

    def beyond(self, cell: int, answer: Answer, toward: int) -> int | None:
        """The cell of the nearest returned point on the given side of ``cell``, if there is one."""
        found = [c for c in (self.cell_of(x) for x in answer.xs.tolist()) if c is not None and (c - cell) * toward > 0]
        return (min(found) if toward > 0 else max(found)) if found else None

    def first_open(self, cell: int, answer: Answer, toward: int) -> int | None:
        """The first cell on the given side that the answer doesn't certify as empty."""
        if not math.isfinite(answer.radius):
            return None
        reach = math.floor((answer.x + toward * answer.radius - self.low) / self.side)
        c = max(cell + 1, reach) if toward > 0 else min(cell - 1, reach)
        return c if 0 <= c < self.n else None

    def nearest_sparse(self, cell: int, toward: int) -> int | None:
        i = bisect.bisect_left(self.sparse, cell)
        if toward > 0:
            return self.sparse[i] if i < len(self.sparse) else None
        return self.sparse[i - 1] if i else None

    def random_unknown(self, rng: random.Random) -> int | None:
        if len(self.state) >= self.n:
            return None
        for _ in range(64):
            c = rng.randrange(self.n)
            if c not in self.state:
                return c
        left = [c for c in range(self.n) if c not in self.state]
        return rng.choice(left) if left else None

    def known(self, cell: int) -> bool | None:
        return self.state.get(cell)


class Restart(Exception):
    """The line was refined while a segment was sought."""


class Pursuit:
    """Finds segments on a line until nothing is unknown or the budget is used up."""

    def __init__(
        self, line, service, n_check: int = 5, strategy: str = "auto", seeds_per_round: int = 1, seed: int = 42,
        on_split: str = "restart", chase_failed: bool = False,
    ):
        if strategy not in STRATEGIES:
            raise ValueError(f"strategy must be one of {STRATEGIES}")
        if on_split not in ("restart", "continue"):
            raise ValueError("on_split must be restart or continue")
        self.line, self.service, self.n_check, self.strategy = line, service, n_check, strategy
        self.seeds_per_round, self.rng, self.on_split = seeds_per_round, random.Random(seed), on_split
        self.segments: list[tuple[int, int]] = []  # first and last cell, by name
        self.partial: list[tuple[int, int]] = []
        self.checks_failed, self.wasted, self.chase_failed = 0, 0, chase_failed
        self.queue: list[int] = []
        self.walked: set[int] = set()

    # --- searches: generators that yield [(cell, purpose)] and get the answers
    def _ask(self, cells: Iterable[tuple[int, str]]) -> Generator:
        version = self.line.version
        answers = yield list(cells)
        if self.line.version != version and self.on_split == "restart":
            raise Restart
        return answers

    def _first_dense(self, start: int | None, q: int, toward: int) -> Generator:
        """The outermost dense cell found from the sparse cell ``start`` (None: the line's end) toward ``q``."""
        line = self.line
        end = -1 if toward > 0 else line.size()
        outer = end if start is None else line.rank(start)
        goal = line.rank(q)
        if self.strategy == "bisect":
            return (yield from self._bisect(start, q, toward))
        if self.strategy == "walk":
            return (yield from self._walk(outer, q, toward))
        pos = outer + toward
        while (goal - pos) * toward > 0:
            cell = line.at(pos)
            state, answer = line.known(cell), None
            if state is None:
                (answer,) = yield from self._ask([(cell, "walk")])
                goal = line.rank(q)
                cell = line.at(min(line.size() - 1, pos)) if line.known(cell) is None else cell
                state = line.known(cell)
                if state is None:
                    continue  # it was split: look at its first part
                pos = line.rank(cell)
            if state:
                return cell
            if answer is None:
                pos += toward
                continue
            nxt = line.beyond(cell, answer, toward)
            if nxt is not None and (line.rank(nxt) - goal) * toward < 0:
                if line.known(nxt) is None:
                    yield from self._ask([(nxt, "walk")])
                    goal = line.rank(q)
                if line.known(nxt):
                    return nxt
                if line.known(nxt) is False:  # noise between here and the cluster
                    if self.strategy == "auto":
                        return (yield from self._bisect(nxt, q, toward))
                    pos = line.rank(nxt) + toward
                continue
            jump = line.first_open(cell, answer, toward)
            if jump is None:
                return q
            pos = max(pos + toward, line.rank(jump)) if toward > 0 else min(pos + toward, line.rank(jump))
            if answer is not None and self.service.calls:
                self.service.calls[-1]["purpose"] = "skip" if self.service.calls[-1]["purpose"] == "walk" else self.service.calls[-1]["purpose"]
        return q

    def _walk(self, outer: int, q: int, toward: int) -> Generator:
        """The first dense cell from rank ``outer`` on: every cell is asked once, whatever answers to others tell of it."""
        line, pos = self.line, outer + toward
        while (line.rank(q) - pos) * toward > 0:
            cell = line.at(pos)
            if line.known(cell) is None or cell not in self.walked:
                yield from self._ask([(cell, "walk")])
                if line.known(cell) is None:
                    continue  # it was split: look at its first part
                self.walked.add(cell)
                pos = line.rank(cell)
            if line.known(cell):
                return cell
            pos += toward
        return q

    def _bisect(self, start: int | None, q: int, toward: int) -> Generator:
        """A dense cell whose neighbour on the outer side is sparse or the end, between a sparse and a dense one."""
        line = self.line
        sparse, dense = start, q
        while True:
            lo = (-1 if toward > 0 else line.size()) if sparse is None else line.rank(sparse)
            hi = line.rank(dense)
            if abs(hi - lo) <= 1:
                return dense
            cell = line.at((lo + hi) // 2)
            if line.known(cell) is None:
                yield from self._ask([(cell, "bisect")])
            state = line.known(cell)
            if state is None:
                continue  # it was split
            if state:
                dense = cell
            else:
                sparse = cell

    def _check(self, d: int, q: int) -> Generator:
        """None if a random sample of the cells between a candidate and q is dense, else a sparse one of them."""
        line = self.line
        lo, hi = sorted((line.rank(d), line.rank(q)))
        if hi - lo < 2:
            return None
        if hi - lo - 1 <= 4 * self.n_check:
            inner = list(range(lo + 1, hi))
            picks = inner if self.n_check >= len(inner) else self.rng.sample(inner, self.n_check)
        else:
            picks = self.rng.sample(range(lo + 1, hi), self.n_check)
        cells = [line.at(r) for r in picks]
        unknown = [c for c in cells if line.known(c) is None]
        bad = [c for c in cells if line.known(c) is False]
        if not bad and unknown:
            yield from self._ask([(c, "check") for c in unknown])
            bad = [c for c in unknown if line.known(c) is False]
        if not bad:
            return None
        self.checks_failed += 1
        return min(bad, key=lambda c: abs(line.rank(c) - line.rank(q)))

    def _boundary(self, q: int, toward: int) -> Generator:
        """The end of q's segment on the side from which ``toward`` leads to q."""
        start = self.line.nearest_sparse(q, -toward)
        while True:
            d = yield from self._first_dense(start, q, toward)
            bad = yield from self._check(d, q)
            if bad is None:
                return d
            if self.chase_failed:
                self.queue.append(d)
            start = bad

    def _segment(self, seed: int) -> Generator:
        while True:
            try:
                if self.line.known(seed) is None:
                    yield from self._ask([(seed, "seed")])
                    if self.line.known(seed) is None:
                        raise Restart
                if not self.line.known(seed):
                    return None
                lo = yield from self._boundary(seed, 1)
                hi = yield from self._boundary(seed, -1)
                return lo, hi
            except Restart:
                seed = self.line.current(seed) if hasattr(self.line, "current") else seed

    # --- rounds
    def run(self) -> Pursuit:
        line, active, waiting = self.line, [], []
        try:
            while True:
                while len(active) < self.seeds_per_round:
                    seed = self._next_seed()
                    if seed is None:
                        break
                    search = self._segment(seed)
                    try:
                        active.append((search, next(search)))
                    except StopIteration as done:
                        self._record(done.value)
                if not active:
                    break
                wanted, order = {}, []
                for _, cells in active:
                    for cell, purpose in cells:
                        if cell in wanted:
                            self.wasted += 0
                        elif line.known(cell) is None or (purpose == "walk" and self.strategy == "walk"):
                            wanted[cell] = purpose
                            order.append(cell)
                found: dict[int, Answer] = {}
                if order:
                    before = len(self.service.calls)  # learning may make further calls, after those of the round
                    got = self.service.probe([line.place(c) for c in order], [wanted[c] for c in order])
                    for i, (cell, answer) in enumerate(zip(order, got)):
                        found[cell] = answer
                        if line.known(cell) is None:
                            self.service.calls[before + i]["node"] = line.learn(cell, answer)
                        else:  # another answer of this round has told already
                            self.wasted += 1
                            self.service.calls[before + i]["node"] = "leaf"
                    if len(got) < len(order):
                        raise BudgetExhausted
                waiting, active = active, []
                for search, cells in waiting:
                    try:
                        active.append((search, search.send([found.get(c) for c, _ in cells])))
                    except StopIteration as done:
                        self._record(done.value)
        except BudgetExhausted:
            for search, _ in [*active, *waiting]:
                search.close()
        return self

    def _next_seed(self) -> int | None:
        while self.queue:
            q = self.queue.pop()
            if not self._covered(q):
                return q
        for _ in range(200):
            q = self.line.random_unknown(self.rng)
            if q is None:
                break
            if not self._covered(q):
                return q
        # cells known to be dense by inference, but in no segment yet
        for q, dense in list(self.line.state.items()):
            if dense and not self._covered(q):
                return q
        return None

    def _covered(self, cell: int) -> bool:
        r = self.line.rank(cell)
        return any(self.line.rank(lo) <= r <= self.line.rank(hi) for lo, hi in self.segments)

    def _record(self, segment: tuple[int, int] | None) -> None:
        if segment is not None and segment not in self.segments:
            self.segments.append(segment)


def boundary_cluster_1d(
    service, domain: tuple[float, float], eps: float, min_pts: int, n_check: int | None = 5, strategy: str = "auto",
    infer: bool = True, seeds_per_round: int = 1, seed: int = 42, rule: str = "min_pts", chase_failed: bool = False,
) -> Pursuit:
    """Dense segments of one-dimensional points; ``n_check=None`` checks every cell."""
    line = GridLine(*domain, eps, min_pts, rule, infer)
    checks = line.n if n_check is None else n_check
    return Pursuit(line, service, checks, strategy, seeds_per_round, seed, chase_failed=chase_failed).run()


def miss_probability(m: int, g: int, c: int) -> float:
    """The chance that c of m cells, drawn without return, miss all g sparse ones."""
    return math.comb(m - g, c) / math.comb(m, c) if 0 <= c <= m else 0.0


def theory_bound(h: int, n_check: int, cells: int) -> float:
    """The order of the calls needed: checks and one logarithmic search for each segment."""
    return h * n_check + h * math.log2(max(2, cells))
