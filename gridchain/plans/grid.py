"""Station grids of the four families: where each record goes, and how often it is copied."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

FAMILIES = {"ds": "1.5D, dense operands move", "ss": "1.5D, the sparse operand moves", "rd": "2.5D, a dense operand is replicated", "rs": "2.5D, the sparse operand is replicated"}
#: Not built: replicating the sparse operand in 1.5D is never better than doing so in 2.5D.
NOT_BUILT = {"15_sparse_replicate": "inferior to the 2.5D family that replicates the sparse operand"}


@dataclass(frozen=True)
class Grid:
    """p stations, c of them on each fiber; m, n, r fix the block sizes. p counts memory domains, not cores."""

    family: str
    p: int
    c: int
    m: int
    n: int
    r: int
    station_order: str = "layer"

    def __post_init__(self):
        if self.family not in FAMILIES:
            raise ValueError(f"unknown family {self.family}: {NOT_BUILT.get(self.family, 'choose one of ' + ', '.join(FAMILIES))}")
        if (why := refusal(self.family, self.p, self.c, self.r)):
            raise ValueError(why)

    @property
    def q(self) -> int:
        return math.isqrt(self.p // self.c)

    @property
    def layer(self) -> int:
        return self.p // self.c

    @property
    def slabs(self) -> int:
        return {"ds": 1, "ss": self.layer, "rd": self.q, "rs": self.q * self.c}[self.family]

    def station(self, at: Column, fiber: Column) -> Column:
        """Number of a station from its place in the layer and on the fiber."""
        number = at * self.c + fiber if self.station_order == "layer" else fiber * self.layer + at
        return number.cast("int")

    @property
    def turned(self) -> Grid:
        """The same stations over the transposed matrix."""
        return Grid(self.family, self.p, self.c, self.n, self.m, self.r, self.station_order)

    def holders(self, what: str) -> int:
        """Stations at which a nonzero ('cell'), or a slab of a row-side or column-side result ('left', 'right'), is worked on."""
        by_family = {
            "ds": {"cell": 1, "left": self.c, "right": self.layer},
            "ss": {"cell": self.layer, "left": self.c, "right": 1},
            "rd": {"cell": self.q, "left": self.c, "right": self.q},
            "rs": {"cell": self.c, "left": self.q, "right": self.q},
        }
        return by_family[self.family][what]

    def slab_bounds(self) -> list[tuple[int, int]]:
        """(first column, width) of each slab; widths differ by one at most."""
        edges = [k * self.r // self.slabs for k in range(self.slabs + 1)]
        return [(a, b - a) for a, b in zip(edges, edges[1:])]


def refusal(family: str, p: int, c: int, r: int) -> str:
    """Why a grid can't be laid out; empty if it can."""
    if c < 1 or p % c:
        return f"the replication factor {c} doesn't divide {p} stations"
    if family in ("rd", "rs") and math.isqrt(p // c) ** 2 != p // c:
        return f"{p}/{c} isn't a square, as a 2.5D grid needs"
    slabs = {"ds": 1, "ss": p // c, "rd": math.isqrt(p // c), "rs": math.isqrt(p // c) * c}.get(family, 1)
    return f"{r} columns can't be cut into {slabs} slabs" if slabs > r else ""


def block(key: str | Column, blocks: int, rows: int) -> Column:
    """Block of an id; sizes differ by one at most. Blocks of unequal sizes at the end are legal."""
    key = F.col(key) if isinstance(key, str) else key
    return F.floor(key * F.lit(blocks) / F.lit(rows)).cast("int")


def visited(packed: DataFrame, grid: Grid) -> DataFrame:
    """Packed nonzeros (home, ...) with a station and the number of the visit, one row for each station they visit; as place_sparse does for single ones."""
    q, c, home = grid.q, grid.c, F.col("home")
    by_layer = grid.station_order == "layer"
    at, fiber = (F.floor(home / c), F.pmod(home, F.lit(c))) if by_layer else (F.pmod(home, F.lit(grid.layer)), F.floor(home / grid.layer))
    copies = {"ds": 1, "ss": grid.layer, "rd": q, "rs": c}[grid.family]
    rows = packed.select("*", _every(copies).alias("visit"))
    visit = F.col("visit")
    where = {"ds": (at, fiber), "ss": (visit, fiber), "rd": (F.floor(at / q) * q + visit, fiber), "rs": (at, visit)}[grid.family]
    return rows.withColumn("station", grid.station(*where))


def _every(n: int) -> Column:
    return F.explode(F.sequence(F.lit(0), F.lit(n - 1)))


def _slabbed(d: DataFrame, grid: Grid) -> DataFrame:
    """(id, slab, start, x) for each column slab of a dense matrix; other columns go with every slab."""
    others = [k for k in d.columns if k not in ("id", "x")]
    if grid.slabs == 1:
        return d.select("id", F.lit(0).alias("slab"), F.lit(0).cast("bigint").alias("start"), "x", *others)
    parts = F.array(*[F.struct(F.lit(k).alias("slab"), F.lit(a).cast("bigint").alias("start"), F.slice("x", a + 1, w).alias("x")) for k, (a, w) in enumerate(grid.slab_bounds())])
    return d.select("id", F.explode(parts).alias("part"), *others).select("id", "part.slab", "part.start", "part.x", *others)


def sparse_home(grid: Grid) -> Column:
    """Station that owns a nonzero before anything moves."""
    q, c = grid.q, grid.c
    if grid.family == "ss":
        fine = block("j", grid.p, grid.n)
        return grid.station(F.floor(fine / c), F.pmod(fine, F.lit(c)))
    if grid.family == "rd":
        fine = block("j", q * c, grid.n)
        return grid.station(block("i", q, grid.m) * q + F.floor(fine / c), F.pmod(fine, F.lit(c)))
    if grid.family == "rs":  # coordinates are on the whole fiber, values are spread over it
        return grid.station(block("i", q, grid.m) * q + block("j", q, grid.n), F.pmod(F.col("i") + F.col("j"), F.lit(c)).cast("int"))
    return grid.station(block("i", grid.layer, grid.m), F.pmod(block("j", grid.p, grid.n), F.lit(c)))


def dense_home(grid: Grid, side: str) -> Column:
    """Station that owns a slab (id, slab) of the row-side ('left') or column-side ('right') operand before anything moves."""
    q, c, rows = grid.q, grid.c, grid.m if side == "left" else grid.n
    if grid.family == "ds":
        fine = block("id", grid.p, rows)
        return grid.station(F.floor(fine / c), F.pmod(fine, F.lit(c)))
    if grid.family == "ss":
        return grid.station(F.col("slab"), F.pmod(block("id", grid.p, rows), F.lit(c)))
    if grid.family == "rd":
        fine = block("id", q * c, rows)
        return grid.station(F.floor(fine / c) * q + F.col("slab"), F.pmod(fine, F.lit(c)))
    coarse, deep = block("id", q, rows), F.floor(F.col("slab") / c)
    return grid.station(coarse * q + deep if side == "left" else deep * q + coarse, F.pmod("slab", F.lit(c)))


def place_sparse(s: DataFrame, grid: Grid) -> DataFrame:
    """s with a station and a home; a family that moves s has one row for each station it visits."""
    q, c = grid.q, grid.c
    s = s.withColumn("home", sparse_home(grid))
    kept = s.columns
    if grid.family == "ds":
        return s.withColumn("station", F.col("home"))
    if grid.family == "ss":
        return s.select(*kept, _every(grid.layer).alias("at")).withColumn("station", grid.station(F.col("at"), F.pmod(block("j", grid.p, grid.n), F.lit(c)))).drop("at")
    if grid.family == "rd":
        fine = block("j", q * c, grid.n)
        return s.select(*kept, _every(q).alias("at")).withColumn("station", grid.station(block("i", q, grid.m) * q + F.col("at"), F.pmod(fine, F.lit(c)))).drop("at")
    return s.select(*kept, _every(c).alias("at")).withColumn("station", grid.station(block("i", q, grid.m) * q + block("j", q, grid.n), F.col("at"))).drop("at")


def place_left(a: DataFrame, grid: Grid) -> DataFrame:
    """(station, home, slab, start, i, ax): copies of the row-side operand, with its other columns."""
    others = [k for k in a.columns if k not in ("id", "x")]
    d, q, c = _slabbed(a, grid).withColumn("home", dense_home(grid, "left")), grid.q, grid.c
    if grid.family in ("ds", "ss", "rd"):
        d = d.select("*", _every(c).alias("fiber"))
        at = {"ds": block("id", grid.layer, grid.m), "ss": F.col("slab"), "rd": block("id", q, grid.m) * q + F.col("slab")}[grid.family]
        station = grid.station(at, F.col("fiber"))
    else:
        d = d.select("*", _every(q).alias("other"))
        station = grid.station(block("id", q, grid.m) * q + F.col("other"), F.pmod("slab", F.lit(c)))
    return d.select(station.alias("station"), "home", "slab", "start", F.col("id").alias("i"), F.col("x").alias("ax"), *others)


def place_right(b: DataFrame, grid: Grid) -> DataFrame:
    """(station, home, slab, start, j, bx): copies of the column-side operand, with its other columns."""
    others = [k for k in b.columns if k not in ("id", "x")]
    d, q, c = _slabbed(b, grid).withColumn("home", dense_home(grid, "right")), grid.q, grid.c
    if grid.family == "ds":
        d = d.select("*", _every(grid.layer).alias("other"))
        station = grid.station(F.col("other"), F.pmod(block("id", grid.p, grid.n), F.lit(c)))
    elif grid.family == "ss":
        station = F.col("home")
    else:
        d = d.select("*", _every(q).alias("other"))
        if grid.family == "rd":
            station = grid.station(F.col("other") * q + F.col("slab"), F.pmod(block("id", q * c, grid.n), F.lit(c)))
        else:
            station = grid.station(F.col("other") * q + block("id", q, grid.n), F.pmod("slab", F.lit(c)))
    return d.select(station.alias("station"), "home", "slab", "start", F.col("id").alias("j"), F.col("x").alias("bx"), *others)


def relayout(d: DataFrame, grid: Grid, side: str) -> DataFrame:
    """(station, home, words) of a result's slabs: where its last step leaves them, and where the next call reads them.

    1.5D results lie at home. A 2.5D result that iterations feed back has to move first: with a
    dense copy it lies transposed in its layer, with a sparse copy one place along its ring.
    """
    q, c = grid.q, grid.c
    placed = _slabbed(d, grid).withColumn("home", dense_home(grid, side))
    rows = grid.m if side == "left" else grid.n
    if grid.family == "rd":
        fine = block("id", q * c, rows)
        station = grid.station(F.col("slab") * q + F.floor(fine / c), F.pmod(fine, F.lit(c)))
    elif grid.family == "rs":
        coarse, deep = block("id", q, rows), F.pmod(F.floor(F.col("slab") / c) + 1, F.lit(q))
        station = grid.station(coarse * q + deep if side == "left" else deep * q + coarse, F.pmod("slab", F.lit(c)))
    else:
        station = F.col("home")
    return placed.select(station.alias("station"), "home", F.size("x").cast("double").alias("words"))
