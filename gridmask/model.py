"""Arrays as tables of cells, constraints and queries."""

from __future__ import annotations

import json
import math
from collections.abc import Sequence
from dataclasses import asdict, dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

COLLAPSE = {"max": F.max, "min": F.min, "sum": F.sum, "avg": F.avg, "count": F.count}


@dataclass(frozen=True)
class Dim:
    """A dimension: integer coordinates in [lo, hi)."""

    name: str
    lo: int = 0
    hi: int = 0

    @property
    def extent(self) -> int:
        return max(0, self.hi - self.lo)


@dataclass(frozen=True)
class ArraySpec:
    """Dimensions, the attribute's name and the shape of a regular chunk."""

    dims: tuple[Dim, ...]
    attr: str = "value"
    chunk: tuple[int, ...] = ()
    on_collision: str = "max"
    #: Cells when the spec was fitted; 0: not known. It only helps to choose how finely an index is stored.
    n_cells: int = field(default=0, compare=False)

    @property
    def names(self) -> list[str]:
        return [d.name for d in self.dims]

    @property
    def n(self) -> int:
        return len(self.dims)

    @property
    def chunk_cells(self) -> int:
        return math.prod(self.chunk)

    @property
    def grid(self) -> list[int]:
        """Chunks along each dimension."""
        return [max(1, -(-d.extent // s)) for d, s in zip(self.dims, self.chunk)]

    def to_json(self) -> str:
        return json.dumps(asdict(self))

    @staticmethod
    def from_json(text: str) -> ArraySpec:
        x = json.loads(text)
        return ArraySpec(tuple(Dim(**d) for d in x["dims"]), x["attr"], tuple(x["chunk"]), x["on_collision"], x.get("n_cells", 0))


def as_array(df: DataFrame, dims: dict[str, Column], attr: Column, on_collision: str = "max", name: str = "value") -> DataFrame:
    """Cells of a table: one row per coordinate. Rows with a null coordinate, null or NaN attribute are empty cells.

    Rows at one coordinate collapse by on_collision; "error" keeps rows as they are and check_unique() tells.
    """
    cells = df.select(*[c.cast("long").alias(d) for d, c in dims.items()], attr.cast("double").alias(name))
    for d in dims:
        cells = cells.where(F.col(d).isNotNull())
    cells = cells.where(F.col(name).isNotNull() & ~F.isnan(name))
    return cells if on_collision in ("error", "none") else collapsed(cells, list(dims), on_collision, name)


def collapsed(cells: DataFrame, keys: Sequence[str], on_collision: str = "max", name: str = "value") -> DataFrame:
    """One row for each coordinate; keys are the dimensions and what follows from them."""
    return cells.groupBy(*keys).agg(COLLAPSE[on_collision](name).cast("double").alias(name))


def check_unique(cells: DataFrame, dims: Sequence[str]) -> None:
    if cells.groupBy(*dims).count().where("count > 1").limit(1).count():
        raise ValueError("several rows at one coordinate")


def fit_spec(cells: DataFrame, dims: Sequence[str], chunk: Sequence[int], attr: str = "value", domain: dict[str, tuple[int, int]] | None = None) -> ArraySpec:
    """Spec whose domains are the coordinates that occur: one aggregate, one row to the driver.

    domain: known ends (lo, hi exclusive) of some dimensions, which the coordinates found can only widen.
    """
    ends = [f(d).alias(f"{p}{i}") for i, d in enumerate(dims) for p, f in (("l", F.min), ("h", F.max))]
    row = cells.agg(F.count("*").alias("n"), *ends).first()
    out = []
    for i, d in enumerate(dims):
        lo, hi = (0, 0) if row[f"l{i}"] is None else (row[f"l{i}"], row[f"h{i}"] + 1)
        if domain and d in domain:
            lo, hi = (domain[d] if row[f"l{i}"] is None else (min(lo, domain[d][0]), max(hi, domain[d][1])))
        out.append(Dim(d, lo, max(lo, hi)))
    return ArraySpec(tuple(out), attr, tuple(chunk), n_cells=row["n"])


@dataclass(frozen=True)
class Constraint:
    """A range with inclusive or exclusive bounds, or a set of values; None leaves a side open."""

    lo: float | None = None
    hi: float | None = None
    lo_incl: bool = True
    hi_incl: bool = False
    values: tuple[float, ...] | None = None

    @staticmethod
    def between(lo, hi, hi_incl: bool = False) -> Constraint:
        return Constraint(lo, hi, True, hi_incl)

    @staticmethod
    def at_least(lo) -> Constraint:
        return Constraint(lo=lo)

    @staticmethod
    def below(hi) -> Constraint:
        return Constraint(hi=hi)

    @staticmethod
    def at_most(hi) -> Constraint:
        return Constraint(hi=hi, hi_incl=True)

    @staticmethod
    def eq(v) -> Constraint:
        return Constraint.isin([v])

    @staticmethod
    def isin(values) -> Constraint:
        return Constraint(values=tuple(sorted(set(values))))

    @property
    def empty(self) -> bool:
        if self.values is not None:
            return not self.values
        if self.lo is None or self.hi is None:
            return False
        return self.lo > self.hi or self.lo == self.hi and not (self.lo_incl and self.hi_incl)

    def column(self, c: Column) -> Column:
        """The plain predicate."""
        if self.values is not None:
            return c.isin(*self.values) if self.values else F.lit(False)
        out = F.lit(True)
        if self.lo is not None:
            out = out & (c >= self.lo if self.lo_incl else c > self.lo)
        if self.hi is not None:
            out = out & (c <= self.hi if self.hi_incl else c < self.hi)
        return out


def to_ranges(c: Constraint, integral: bool) -> list[Constraint]:
    """A constraint as disjoint ranges in ascending order: a set of integers becomes its maximal runs."""
    if c.values is None:
        return [] if c.empty else [c]
    out: list[Constraint] = []
    for v in c.values:
        if integral and out and v == out[-1].hi + 1:
            out[-1] = replace(out[-1], hi=v)
        else:
            out.append(Constraint.between(v, v, hi_incl=True))
    return out


@dataclass(frozen=True)
class ArrayQuery:
    """Constraints on dimensions by name and on the attribute; what is missing is unconstrained."""

    dims: dict[str, Constraint] = field(default_factory=dict)
    attr: Constraint = field(default_factory=Constraint)

    def predicate(self, spec: ArraySpec) -> Column:
        out = self.attr.column(F.col(spec.attr))
        for d, c in self.dims.items():
            out = out & c.column(F.col(d))
        return out


@dataclass(frozen=True)
class Region:
    """Normal form of a query: for each dimension disjoint half-open runs of coordinates, and disjoint attribute ranges."""

    dims: tuple[tuple[tuple[int, int], ...], ...]
    attr: tuple[Constraint, ...]

    @property
    def empty(self) -> bool:
        return not self.attr or not all(self.dims)


def complete_query(q: ArrayQuery, spec: ArraySpec) -> Region:
    """Fill open sides and missing dimensions from the domain, clip to it, make upper bounds exclusive; sets become runs."""
    unknown = set(q.dims) - set(spec.names)
    if unknown:
        raise ValueError(f"unknown dimensions: {sorted(unknown)}")
    dims = []
    for d in spec.dims:
        runs = []
        for c in to_ranges(q.dims.get(d.name, Constraint()), True):
            a = d.lo if c.lo is None else math.ceil(c.lo) + (not c.lo_incl and float(c.lo).is_integer())
            b = d.hi if c.hi is None else (math.floor(c.hi) + 1 if c.hi_incl else math.ceil(c.hi))
            a, b = max(a, d.lo), min(b, d.hi)
            if a < b:
                runs.append((a, b))
        dims.append(tuple(runs))
    return Region(tuple(dims), tuple(to_ranges(q.attr, False)))
