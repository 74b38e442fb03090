"""The kernels and the chain on station grids, with either saving between the two kernels.

A family is a placement; the local kernels are the same for all of them (station.py). What
a variant saves is an exchange that its plan does not have:

none    the masked product, stored; then the gather, which gets its dense operand again.
reuse   the copied operand is dealt to its fiber once and serves both kernels.
fuse    one pass: where whole rows meet, dots weight rows at once, nothing lies between.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridchain.operators.matrix import stats, transpose
from gridchain.operators.station import DOTS, LEFT, PARTIAL, RIGHT, at_stations, cell_rows, chain_kernel, chunk_rows, deal, dense_rows, finished, gather_kernel, masked_kernel, packed, reduced, unpacked
from gridchain.plans import planner
from gridchain.plans.grid import Grid, place_left, place_right, place_sparse, sparse_home, visited
from gridchain.sources.scratch import stored

ELISIONS = {"ds": ("none", "reuse", "fuse"), "ss": ("none", "reuse"), "rd": ("none", "reuse"), "rs": ("none",)}


def check_elision(family: str, elision: str, softmax: bool = False) -> None:
    """Refuses what can't be right, with the reason."""
    if softmax and "fuse" in elision:
        raise ValueError("a softmax over a whole row stands between the kernels, so they can't be fused")
    if elision in ("reuse+fuse", "fuse+reuse"):
        raise ValueError("reuse and fuse exclude each other: together they need one more moving accumulator")
    if elision not in ELISIONS[family]:
        if elision == "fuse":
            raise ValueError(f"{family} cuts dense rows into column slabs; partial dots can't weight rows yet, so it can't fuse")
        if elision == "reuse":
            raise ValueError(f"{family} replicates no dense operand that could be reused")
        raise ValueError(f"unknown elision {elision}")


def _left(a: DataFrame, grid: Grid) -> DataFrame:
    return deal(dense_rows(place_left(a, grid), LEFT, "i", "ax"), grid.p)


def _right(b: DataFrame, grid: Grid) -> DataFrame:
    return deal(dense_rows(place_right(b, grid), RIGHT, "j", "bx"), grid.p)


def _packed(s: DataFrame, grid: Grid) -> DataFrame:
    return packed(s.select("i", "j", "v", sparse_home(grid).alias("home")))


def _dealt(chunks: DataFrame, grid: Grid) -> DataFrame:
    return deal(chunk_rows(visited(chunks, grid)), grid.p)


def _cells(s: DataFrame, grid: Grid) -> DataFrame:
    return _dealt(_packed(s, grid), grid)


def _products(cells: DataFrame, left: DataFrame, right: DataFrame, grid: Grid, scaled: bool, pair=None) -> DataFrame:
    """Packed masked product; dots over slabs that lie at several stations are summed by nonzero, a chunk at a time."""
    return finished(at_stations([left, right, cells], masked_kernel(pair), DOTS), scaled, grid.holders("cell") > 1)


def _gathered(cells: DataFrame, dense: DataFrame, grid: Grid, out: str) -> DataFrame:
    partial = at_stations([dense, cells], gather_kernel(RIGHT if out == "left" else LEFT), PARTIAL)
    return reduced(partial, grid.holders(out) == 1)


def masked(s: DataFrame, a: DataFrame, b: DataFrame, grid: Grid, scaled: bool = True, pair: tuple[list[float], list[float]] | None = None) -> DataFrame:
    """s_ij * <a_i, b_j> on the grid; with a pair (u, v) the dot is u . a_i + v . b_j, which moves the same rows."""
    return unpacked(_products(_cells(s, grid), _left(a, grid), _right(b, grid), grid, scaled, pair))


def gather(side: str, s: DataFrame, d: DataFrame, grid: Grid) -> DataFrame:
    """Long form of s * d (side 'left') or s' * d (side 'right'); partial rows of several stations meet in the last exchange."""
    return _gathered(_cells(s, grid), _right(d, grid) if side == "left" else _left(d, grid), grid, side)


class PlacedChain:
    """A chain over one pattern and one fixed factor: both are dealt to their stations once, for any number of calls.

    Calling it with rows (id, x) gives the long form of masked(s, x, b) * b. The dealt rows
    are persisted on disk; what a lost executor held is dealt again from its source.
    """

    def __init__(self, s: DataFrame, b: DataFrame, grid: Grid, elision: str = "none", scaled: bool = True, keep: bool = True):
        check_elision(grid.family, elision)
        whole = elision == "fuse" or grid.family == "ds" and elision == "reuse"
        if whole and not scaled:
            s = s.withColumn("v", F.lit(1.0))  # a whole dot weights its row at the station, so the scale is set there
        # roles change for reuse, over the transposed copy: b lies on its fiber and serves both kernels
        self.grid = grid.turned if elision == "reuse" else grid
        self.elision, self.scaled, self.whole, self.b = elision, scaled, whole, b
        self.cells = _cells(transpose(s) if elision == "reuse" else s, self.grid)
        self.fixed = _left(b, self.grid) if elision == "reuse" else _right(b, self.grid)
        if keep:
            self.cells, self.fixed = (x.persist(StorageLevel.DISK_ONLY) for x in (self.cells, self.fixed))

    def __call__(self, a: DataFrame) -> DataFrame:
        grid = self.grid
        if self.elision == "reuse":
            moving = _right(a, grid)
            if self.whole:  # both kernels run where the copy lies; the result travels
                return reduced(at_stations([self.fixed, moving, self.cells], chain_kernel(LEFT), PARTIAL), grid.holders("right") == 1)
            r = _products(self.cells, self.fixed, moving, grid, self.scaled)
            return _gathered(_dealt(r, grid), self.fixed, grid, "right")
        if self.elision == "fuse":
            return reduced(at_stations([_left(a, grid), self.fixed, self.cells], chain_kernel(RIGHT), PARTIAL), grid.holders("left") == 1)
        r = stored(_products(self.cells, _left(a, grid), self.fixed, grid, self.scaled), "masked")
        return _gathered(_dealt(r, grid), _right(self.b, grid), grid, "left")

    def release(self) -> None:
        self.cells.unpersist()
        self.fixed.unpersist()


def chain_left(s: DataFrame, a: DataFrame, b: DataFrame, grid: Grid, elision: str = "none", scaled: bool = True) -> DataFrame:
    """Long form of masked(s, a, b) * b. The grid's m and n are those of s."""
    return PlacedChain(s, b, grid, elision, scaled, keep=False)(a)


def chain_right(s: DataFrame, a: DataFrame, b: DataFrame, grid: Grid, elision: str = "none", scaled: bool = True) -> DataFrame:
    """Long form of masked(s, a, b)' * a, through the transposed copy."""
    return chain_left(transpose(s), b, a, grid.turned, elision, scaled)


@dataclass(frozen=True)
class Choice:
    """What a chain runs on; grid is None where single rows are fetched by plain joins."""

    grid: Grid | None
    elision: str


def choose(s: DataFrame, p: int, r: int, m: int | None = None, n: int | None = None, nnz: int | None = None, family: str = "auto", elision: str = "auto", c: int | None = None, cap: int | None = 16, memory: float | None = None, remote_rows: int | None = None, softmax: bool = False) -> Choice:
    """The planner's grid for this matrix; what is given is kept. One aggregate runs unless m, n and nnz are known.

    With remote_rows (baselines.remote_rows) plain joins are chosen where single rows move clearly less.
    """
    if None in (m, n, nnz):
        found = stats(s, r, m, n)
        m, n, nnz = found.m, found.n, found.nnz
    rows = [x for x in planner.candidates(p, n, r, nnz, cap, memory) if x[7] is None and family in ("auto", x[0]) and elision in ("auto", x[1]) and c in (None, x[3]) and not (softmax and x[1] == "fuse")]
    if not rows:
        raise ValueError(f"no grid of {p} stations is admissible for family {family}, elision {elision}, c {c}")
    best = min(rows, key=lambda x: (round(x[4], 9), x[3]))
    if family == "auto" and remote_rows is not None and planner.prefer_fetch(remote_rows, r, p, best[4]):
        return Choice(None, "fetch")
    return Choice(Grid(best[0], p, best[3], m, n, r), best[1])


def chain(s: DataFrame, a: DataFrame, b: DataFrame, p: int, r: int, side: str = "left", scaled: bool = True, **wanted) -> DataFrame:
    """The chain on the planner's choice; wanted may fix the family, the elision, c or the shape (see choose)."""
    from gridchain.operators.kernels import chain_long

    found = choose(s, p, r, **wanted)
    if found.grid is None:
        s = s if scaled else s.withColumn("v", F.lit(1.0))
        return chain_long(s, a, b) if side == "left" else chain_long(transpose(s), b, a)
    return (chain_left if side == "left" else chain_right)(s, a, b, found.grid, found.elision, scaled)


def chain_phased(s: DataFrame, a: DataFrame, b: DataFrame, grid: Grid) -> DataFrame:
    """Fused 1.5D chain in p/c phases, each a stored job: in phase t a station meets only one block of b.

    The same words of b and of nonzeros move as in the bulk form, but a station holds one block of b at a time.
    """
    if grid.family != "ds":
        raise ValueError("phases are built for the fused dense-moving family")
    layers, out = grid.layer, None
    at = F.floor(F.col("station") / grid.c) if grid.station_order == "layer" else F.pmod("station", F.lit(layers))
    for t in range(layers):
        turn = F.pmod(F.floor(F.col("j") * grid.p / grid.n / grid.c) + t, F.lit(layers)) == at
        right = deal(dense_rows(place_right(b, grid).filter(turn), RIGHT, "j", "bx"), grid.p)
        cells = deal(cell_rows(place_sparse(s, grid).filter(turn)), grid.p)
        part = stored(at_stations([_left(a, grid), right, cells], chain_kernel(RIGHT), PARTIAL), "phase")
        out = part if out is None else out.unionByName(part)
    return reduced(out, False)
