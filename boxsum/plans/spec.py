"""Axes, grids, anchor specifications and the catalog of anchor tables.

An anchor table of a subset S of axes holds cumulative sums: for an axis a in S its column q_a counts steps of
tile * stride cells from the origin, and a row sums all cells below q_a * step; the other axes keep their index.
All bounds are half-open.
"""

from __future__ import annotations

import json
import math
from collections.abc import Iterable, Mapping
from dataclasses import dataclass, field
from itertools import combinations

Subset = tuple[str, ...]
# The keys of the attribute tree.
GROUP, PLAIN, WEIGHTED, WEIGHTS = "_ACCUMULATION_GROUP", "_DATA_UNWEIGHTED", "_DATA_WEIGHTED", "_WEIGHTS"
DIMENSIONS, STRIDE = "_ARRAY_DIMENSIONS", "_ACCUMULATION_STRIDE"
KINDS = {"plain": PLAIN, "weighted": WEIGHTED, "weight": WEIGHTS}


class SpecError(ValueError):
    pass


@dataclass(frozen=True)
class AxisSpec:
    """A regular axis of n cells in tiles; origin and width relate indices to coordinates."""

    name: str
    n: int
    tile: int
    origin: float = 0.0
    width: float = 1.0
    wraps: bool = False

    def span(self, low: float, high: float) -> list[tuple[int, int]]:
        """Index ranges of the cells in [low, high) by coordinate; two where the axis wraps around and low > high."""
        at = lambda v: math.floor((v - self.origin) / self.width + 1e-9)
        a, b = at(low), math.ceil((high - self.origin) / self.width - 1e-9)
        if low > high:
            if not self.wraps:
                raise SpecError(f"{self.name} doesn't wrap around")
            return [r for r in ((max(a, 0), self.n), (0, min(b, self.n))) if r[0] < r[1]]
        a, b = max(a, 0), min(b, self.n)
        return [(a, b)] if a < b else []


@dataclass(frozen=True)
class GridSpec:
    name: str
    axes: tuple[AxisSpec, ...]
    measures: tuple[str, ...] = ("sx", "n")

    def __getitem__(self, name: str) -> AxisSpec:
        try:
            return next(a for a in self.axes if a.name == name)
        except StopIteration:
            raise SpecError(f"no axis {name}") from None

    @property
    def names(self) -> Subset:
        return tuple(a.name for a in self.axes)

    def order(self, names: Iterable[str]) -> Subset:
        """The names in the grid's order."""
        wanted = set(names)
        if extra := wanted - set(self.names):
            raise SpecError(f"no axes {sorted(extra)}")
        return tuple(n for n in self.names if n in wanted)

    @property
    def cells(self) -> int:
        return math.prod(a.n for a in self.axes)


@dataclass(frozen=True)
class AnchorSpec:
    """Which axes a table accumulates, by a stride for each axis of the grid: tiles between anchors, 0 for none."""

    axes: Subset
    stride: tuple[int, ...]

    @property
    def subset(self) -> Subset:
        return tuple(a for a, s in zip(self.axes, self.stride, strict=True) if s)

    def of(self, axis: str) -> int:
        return self.stride[self.axes.index(axis)]

    @classmethod
    def uniform(cls, grid: GridSpec, subset: Iterable[str], stride: int | Mapping[str, int] = 1) -> AnchorSpec:
        subset = grid.order(subset)
        each = stride if isinstance(stride, Mapping) else dict.fromkeys(subset, stride)
        return cls(grid.names, tuple(each.get(a, 1) if a in subset else 0 for a in grid.names))


def validate(attributes: Mapping, grid: GridSpec | None = None) -> AnchorSpec:
    """The specification in a table's attributes; SpecError says what is wrong with them."""
    for key in (DIMENSIONS, STRIDE):
        if key not in attributes:
            raise SpecError(f"{key} is missing")
    names, strides = attributes[DIMENSIONS], attributes[STRIDE]
    if len(names) != len(strides):
        raise SpecError("dimensions and strides differ in number")
    if len(set(names)) != len(names) or not all(isinstance(n, str) for n in names):
        raise SpecError("dimension names must be different strings")
    if not all(isinstance(s, int) and not isinstance(s, bool) and s >= 0 for s in strides):
        raise SpecError("strides must be whole numbers from 0")
    if not any(strides):
        raise SpecError("no axis is accumulated")
    if grid is not None and tuple(names) != grid.names:
        raise SpecError(f"dimensions must be {list(grid.names)} in this order")
    return AnchorSpec(tuple(names), tuple(strides))


def array_name(subset: Iterable[str], kind: str = "plain") -> str:
    return {"plain": "acc_", "weighted": "acc_weighted_", "weight": "acc_wt_"}[kind] + "_".join(subset)


def usable(over: Subset, present: Iterable[Subset]) -> Subset:
    """The most axes of `over` all of whose subsets are there; of as many the first."""
    have = set(present)
    for k in range(len(over), 0, -1):
        for some in combinations(over, k):
            if all(c in have for j in range(1, k + 1) for c in combinations(some, j)):
                return some
    return ()


def subsets_for(services: Iterable[Iterable[str]], grid: GridSpec) -> list[Subset]:
    """All subsets that averages over the given sets of axes can use, smaller ones first."""
    found = {grid.order(c) for d in services for k in range(1, len(set(d)) + 1) for c in combinations(grid.order(d), k)}
    return sorted(found, key=lambda s: (len(s), [grid.names.index(a) for a in s]))


@dataclass
class AnchorCatalog:
    """Which anchor tables there are, with their kinds, places and strides."""

    grid: GridSpec
    entries: dict[Subset, dict] = field(default_factory=dict)

    def add(self, spec: AnchorSpec, kinds: Iterable[str] = ("plain",), rows: int | None = None, names: Mapping[str, str] | None = None) -> None:
        """A subset's tables, one a kind; `names` where they are not called as usual."""
        if spec.axes != self.grid.names:
            raise SpecError("the grid has other axes")
        if unknown := set(kinds) - set(KINDS):
            raise SpecError(f"unknown kinds {sorted(unknown)}")
        self.entries[spec.subset] = {"spec": spec, "names": {k: (names or {}).get(k) or array_name(spec.subset, k) for k in kinds}, "rows": rows}

    def find(self, names: Iterable[str], kind: str = "plain") -> str | None:
        """The name of a table by its axes in any order; None if it isn't there or lacks the kind."""
        e = self.entries.get(self.grid.order(names))
        return e["names"].get(kind) if e else None

    def stride(self, names: Iterable[str]) -> dict[str, int]:
        s = self.entries[self.grid.order(names)]["spec"]
        return {a: s.of(a) for a in s.subset}

    def anchor_of(self, names: Iterable[str], axis: str, tile: int) -> int:
        """The anchor at or below a tile's leading face."""
        return tile // self.stride(names)[axis]

    def rows(self) -> list[tuple]:
        """(subset, kind, name, stride) of every table and kind."""
        return [(list(s), k, name, self.stride(s)) for s, e in sorted(self.entries.items(), key=lambda x: (len(x[0]), x[0])) for k, name in e["names"].items()]

    def to_json(self) -> str:
        axes = [{"name": a.name, "n": a.n, "tile": a.tile, "origin": a.origin, "width": a.width, "wraps": a.wraps} for a in self.grid.axes]
        tables = [{"subset": list(s), "stride": list(e["spec"].stride), "names": e["names"], "rows": e["rows"]} for s, e in self.entries.items()]
        return json.dumps({"grid": self.grid.name, "measures": list(self.grid.measures), "axes": axes, "tables": tables}, indent=1)

    @classmethod
    def from_json(cls, text: str) -> AnchorCatalog:
        raw = json.loads(text)
        out = cls(GridSpec(raw["grid"], tuple(AxisSpec(**a) for a in raw["axes"]), tuple(raw["measures"])))
        for t in raw["tables"]:
            spec = validate({DIMENSIONS: list(out.grid.names), STRIDE: t["stride"]}, out.grid)
            if list(spec.subset) != t["subset"]:
                raise SpecError(f"strides are positive on {spec.subset}, not {t['subset']}")
            out.add(spec, t["names"], t["rows"], t["names"])
        return out

    def export_attributes(self) -> dict:
        """The tree of tables nested by axis names in order; a combination that is absent is an empty node."""

        def node(prefix: Subset) -> dict:
            e = self.entries.get(prefix)
            out = {} if e is None else {KINDS[k]: name for k, name in e["names"].items()}
            last = self.grid.names.index(prefix[-1]) if prefix else -1
            for a in self.grid.names[last + 1 :]:
                out[a] = node((*prefix, a))
            return out

        return {GROUP: node(())}

    def array_attributes(self, names: Iterable[str]) -> dict:
        """The attributes of a subset's tables: all axes, and the strides along them."""
        return {DIMENSIONS: list(self.grid.names), STRIDE: list(self.entries[self.grid.order(names)]["spec"].stride)}

    @staticmethod
    def import_attributes(tree: Mapping) -> dict[tuple[Subset, str], str]:
        """(subset, kind) to table name from such a tree; unknown keys and kinds are refused."""
        if set(tree) != {GROUP}:
            raise SpecError(f"only {GROUP} may be at the root, and must be")
        kinds = {v: k for k, v in KINDS.items()}
        found: dict[tuple[Subset, str], str] = {}

        def walk(node: Mapping, prefix: Subset) -> None:
            for key, value in node.items():
                if key in kinds:
                    if not prefix or not isinstance(value, str):
                        raise SpecError(f"{key} must be a name under an axis")
                    found[prefix, kinds[key]] = value
                elif key.startswith("_") or not isinstance(value, Mapping) or key in prefix:
                    raise SpecError(f"unknown key {key}")
                else:
                    walk(value, (*prefix, key))

        walk(tree[GROUP], ())
        return found


def common_step(grid: GridSpec, specs: Iterable[AnchorSpec], axis: str) -> int:
    """Cells between the anchors of an axis that all these tables have in common."""
    strides = [s.of(axis) for s in specs if s.of(axis)]
    if not strides:
        raise SpecError(f"no table accumulates {axis}")
    return grid[axis].tile * math.lcm(*strides)
