"""From a box and a catalog to scans: which anchors and gap cells to read, and with what signs.

The range [lo, hi) of an averaged axis is a signed sum of pieces: the anchor of each end and the gap between
anchor and end. The box is the product over axes; collecting the terms by the axes whose piece is an anchor
gives one filtered scan a subset, with the row's sign the product of its pieces' signs.
"""

from __future__ import annotations

import math
from collections.abc import Iterable, Mapping
from dataclasses import dataclass
from itertools import chain, combinations, product

from boxsum.plans.spec import AnchorSpec, GridSpec, SpecError, Subset, common_step

Range = tuple[int, int]


@dataclass(frozen=True)
class End:
    q: int
    low: int
    high: int
    sign: int


def split_endpoint(e: int, step: int, n: int, mode: str = "floor") -> End:
    """Anchor, gap and the gap's sign of an end. "nearest" takes the anchor above if it is there and nearer."""
    if not 0 <= e <= n:
        raise SpecError(f"{e} is outside 0..{n}")
    below = e // step
    if mode == "nearest":
        above = (below + 1) * step
        if above <= n and above - e < e - below * step:
            return End(below + 1, e, above, -1)
    elif mode != "floor":
        raise SpecError(f"unknown mode {mode}")
    return End(below, below * step, e, 1)


@dataclass(frozen=True)
class Pieces:
    """Signed anchors (in steps) and signed gap ranges of one axis."""

    anchors: tuple[tuple[int, int], ...]
    gaps: tuple[tuple[int, int, int], ...]


def pieces(lo: int, hi: int, step: int, n: int, mode: str = "floor") -> Pieces:
    if not 0 <= lo < hi <= n:
        raise SpecError(f"[{lo}, {hi}) is no range in 0..{n}")
    a, b = split_endpoint(lo, step, n, mode), split_endpoint(hi, step, n, mode)
    if a.q == b.q:
        return Pieces((), ((lo, hi, 1),))
    anchors = tuple((x.q, s) for x, s in ((b, 1), (a, -1)) if x.q)
    gaps = tuple((x.low, x.high, s * x.sign) for x, s in ((b, 1), (a, -1)) if x.low < x.high)
    return Pieces(anchors, gaps)


@dataclass(frozen=True)
class ScanTerm:
    """One scan: of the table of `subset` (the cells if empty), with the pieces of every averaged axis."""

    subset: Subset
    anchors: Mapping[str, tuple[tuple[int, int], ...]]  # in anchors of that table
    gaps: Mapping[str, tuple[tuple[int, int, int], ...]]
    kept: Mapping[str, Range]

    @property
    def reads(self) -> int:
        return math.prod(chain((len(a) for a in self.anchors.values()), (sum(h - l for l, h, _ in g) for g in self.gaps.values()), (h - l for l, h in self.kept.values())))  # noqa: E741


@dataclass(frozen=True)
class BoxPlan:
    scans: tuple[ScanTerm, ...]
    averaged: Subset
    kept: Subset
    extent: int
    used: Subset  # averaged axes that anchors are used for

    def reads(self) -> int:
        """Rows of anchor tables and cells that the scans read where no row is missing."""
        return sum(t.reads for t in self.scans)

    def by_role(self) -> dict[str, int]:
        return {"anchor": sum(t.reads for t in self.scans if t.subset), "gap": sum(t.reads for t in self.scans if not t.subset)}

    def tiles(self, grid: GridSpec) -> int:
        """Tiles of cells that the scan of cells touches."""
        total = 0
        for t in self.scans:
            if not t.subset:
                per_axis = [len({i // grid[a].tile for l, h, _ in g for i in range(l, h)}) for a, g in t.gaps.items()]  # noqa: E741
                per_axis += [(h - 1) // grid[a].tile - l // grid[a].tile + 1 for a, (l, h) in t.kept.items()]  # noqa: E741
                total += math.prod(per_axis)
        return total


def plan_box(grid: GridSpec, specs: Mapping[Subset, AnchorSpec], box: Mapping[str, Range], average_over: Iterable[str], mode: str = "floor", scan_cost: int = 0) -> BoxPlan:
    """The cheapest plan: anchors for a set P of averaged axes all of whose subsets are there, plain ranges for the rest.

    A plan's cost is the rows that it reads and `scan_cost` rows for each scan. The mode "best" takes the cheaper
    of "floor" and "nearest".
    """
    over = grid.order(average_over)
    bounds = {a: tuple(box.get(a, (0, grid[a].n))) for a in grid.names}
    if unknown := set(box) - set(grid.names):
        raise SpecError(f"no axes {sorted(unknown)}")
    for a, (lo, hi) in bounds.items():
        if not 0 <= lo < hi <= grid[a].n:
            raise SpecError(f"{a}: [{lo}, {hi}) is no range in 0..{grid[a].n}")
    kept = {a: bounds[a] for a in grid.names if a not in over}
    extent = math.prod(bounds[a][1] - bounds[a][0] for a in over)
    best = None
    modes = ("floor", "nearest") if mode == "best" else (mode,)
    for used, ends in product(chain.from_iterable(combinations(over, k) for k in range(len(over) + 1)), modes):
        subsets = list(chain.from_iterable(combinations(used, k) for k in range(1, len(used) + 1)))
        if not all(s in specs for s in subsets):
            continue
        steps = {a: common_step(grid, [specs[s] for s in subsets], a) for a in used}
        split = {a: pieces(*bounds[a], steps[a], grid[a].n, ends) for a in used}
        terms = []
        for s in [(), *subsets]:
            anchors = {a: tuple((q * steps[a] // (grid[a].tile * specs[s].of(a)), sign) for q, sign in split[a].anchors) for a in s}
            gaps = {a: split[a].gaps for a in used if a not in s} | {a: ((*bounds[a], 1),) for a in over if a not in used}
            if all(anchors.values()) and all(gaps.values()):
                terms.append(ScanTerm(s, anchors, gaps, kept))
        plan = BoxPlan(tuple(terms), over, tuple(kept), extent, used)
        cost = plan.reads() + scan_cost * len(plan.scans), len(plan.scans)
        if best is None or cost < best[0]:
            best = cost, plan
    return best[1]
