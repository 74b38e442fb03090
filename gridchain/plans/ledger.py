"""Words and messages of a chain, counted from the rows that its plan ships."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridchain.plans.grid import Grid, dense_home, place_left, place_right, place_sparse, relayout
from gridchain.plans.grid import _slabbed as slabs_of

LEDGER = ["family", "elision", "stage", "station", "words_ring", "words_remote", "messages"]


@dataclass
class Move:
    """Rows (station, home, words) of one stage.

    ring holds every delivery of the round of shifts that the closed forms count (whole says whether
    the last shift, which brings a block home, counts too); shipped what the exchange carries.
    """

    stage: str
    ring: DataFrame | None
    shipped: DataFrame
    whole: bool


def _words(placed: DataFrame, words) -> DataFrame:
    return placed.select("station", "home", F.lit(words).cast("double").alias("words") if isinstance(words, int) else words.cast("double").alias("words"))


def moves(s: DataFrame, a: DataFrame, b: DataFrame, grid: Grid, elision: str) -> list[Move]:
    """Every stage of chain_left in order, with the placements that the chain itself uses."""
    if elision == "reuse":
        grid, s, a, b = grid.turned, s.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), b, a
    cells, left, right = place_sparse(s, grid), place_left(a, grid), place_right(b, grid)
    out = "right" if elision == "reuse" else "left"
    # one partial row leaves a station for each id and slab that a nonzero of it reaches
    key, placed = ("j", right) if out == "right" else ("i", left)
    partial = placed.join(cells.select("station", key).distinct(), ["station", key], "left_semi")
    vector = "bx" if out == "right" else "ax"
    copied, moving = _words(left, F.size("ax")), _words(right, F.size("bx"))
    result, shipped = _words(placed, F.size(vector)), _words(partial, F.size(vector))
    if grid.family == "rs":
        values = _words(cells, 1)
        first = [Move("fiber values", values, values, False), Move("pass dense", copied, copied, True), Move("pass dense", moving, moving, True)]
        second = [Move("partial dots", values, values, False), Move("fiber values", values, values, False), Move("pass dense", moving, moving, True)]
        return [*first, *second, Move("pass result", result, shipped, True)]
    found = [Move("copy", copied, copied, False)]
    if grid.family in ("ss", "rd"):
        found += [Move("pass sparse", _words(cells, 3), _words(cells, 3), True)] * 2
        found += [Move("partial dots", None, _words(cells, 1), False)]  # ride on the moving nonzeros in a ring
    if grid.family in ("ds", "rd"):
        found += [Move("pass dense", moving, moving, True)] * (2 if elision == "none" else 1)
    if out == "left":
        found += [Move("reduce", result, shipped, False)]
    elif grid.family != "ss":  # there the result stays where it is summed
        found += [Move("pass result", result, shipped, True)]
    return found


def skew(s: DataFrame, a: DataFrame, b: DataFrame, grid: Grid) -> list[DataFrame]:
    """(station, home, words) of the first alignment of what a 2.5D ring shifts: a block moves as many places as its row or column says.

    It is paid once, or not at all if buffers are filled aligned. In Spark a row's key says where it goes, so nothing moves.
    """
    q, c = grid.q, grid.c
    found = []
    if grid.family not in ("rd", "rs"):
        return found
    sides = [("right", b)] if grid.family == "rd" else [("left", a), ("right", b)]
    frames = [(slabs_of(x, grid).withColumn("home", dense_home(grid, side)), F.size("x"), side) for side, x in sides]
    if grid.family == "rd":
        frames.append((place_sparse(s, grid).select("i", "j", "home").distinct(), F.lit(3), "left"))
    for rows, words, side in frames:
        number = F.col("home") if grid.station_order == "layer" else F.pmod("home", F.lit(grid.layer)) * c + F.floor(F.col("home") / grid.layer)
        fiber, at = F.pmod(number, F.lit(c)), F.floor(number / c)
        up, along = F.floor(at / q), F.pmod(at, F.lit(q))
        to = up * q + F.pmod(along + up, F.lit(q)) if side == "left" else F.pmod(up + along, F.lit(q)) * q + along
        found.append(rows.select(grid.station(to, fiber).alias("station"), "home", words.cast("double").alias("words")))
    return found


def chain_ledger(s: DataFrame, a: DataFrame, b: DataFrame, grid: Grid, elision: str, count_skew: bool = False) -> DataFrame:
    """(family, elision, stage, station, words_ring, words_remote, messages) of one chain.

    words_ring is what a station gets in full rounds of shifts, as the closed forms count;
    words_remote what the plan's exchanges bring it from other owners. Messages are blocks
    from different owners. A stage that happens twice has its words twice. count_skew adds
    the first alignment of 2.5D rings, which the closed forms leave out.
    """
    parts = []
    for x in skew(s, a, b, grid) if count_skew else []:
        away = x.filter("station <> home").groupBy("station").agg(F.sum("words").alias("words_ring"), F.count_distinct("home").cast("double").alias("messages"))
        names = [F.lit(grid.family).alias("family"), F.lit(elision).alias("elision"), F.lit("skew").alias("stage")]
        parts.append(away.select(*names, "station", "words_ring", F.lit(0.0).alias("words_remote"), "messages"))
    for x in moves(s, a, b, grid, elision):
        away = F.col("station") != F.col("home")
        counted = F.lit(True) if x.whole else away
        shipped = x.shipped.filter(away).groupBy("station").agg(F.sum("words").alias("words_remote"))
        zero = F.lit(0.0)
        if x.ring is None:
            rows = shipped.select("station", zero.alias("words_ring"), "words_remote", zero.alias("messages"))
        else:
            ring = x.ring.groupBy("station").agg(F.sum(F.when(counted, F.col("words")).otherwise(0.0)).alias("words_ring"), (F.count_distinct(F.when(away, F.col("home"))) + int(x.whole)).cast("double").alias("messages"))
            rows = ring.join(shipped, "station", "left").select("station", "words_ring", F.coalesce("words_remote", zero).alias("words_remote"), "messages")
        parts.append(rows.select(F.lit(grid.family).alias("family"), F.lit(elision).alias("elision"), F.lit(x.stage).alias("stage"), "station", "words_ring", "words_remote", "messages"))
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def iteration_ledger(x: DataFrame, grid: Grid, elision: str, dots: int = 3, side: str = "left") -> DataFrame:
    """What a solver's step pays outside the chain, in the columns of chain_ledger.

    relayout: a 2.5D result moves back to where the next call reads it. row_dot: rows cut into
    slabs sum each of `dots` row-wise products over their slabs.
    """
    back = relayout(x, grid, side)
    held = slabs_of(x, grid).withColumn("station", dense_home(grid, side))
    first = held.withColumn("slab", F.lit(0)).withColumn("home", dense_home(grid, side))
    sums = first.select(F.col("home").alias("station"), F.col("station").alias("home"), F.lit(float(dots)).alias("words"))
    parts = []
    for name, rows in (("relayout", back), ("row_dot", sums)):
        away = rows.filter("station <> home").groupBy("station").agg(F.sum("words").alias("words"), F.count_distinct("home").cast("double").alias("messages"))
        parts.append(away.select(F.lit(grid.family).alias("family"), F.lit(elision).alias("elision"), F.lit(name).alias("stage"), "station", F.col("words").alias("words_ring"), F.col("words").alias("words_remote"), "messages"))
    return parts[0].unionByName(parts[1])


def words(ledger: DataFrame) -> DataFrame:
    """The largest and the mean words of a station, and what the exchanges bring all stations."""
    by_station = ledger.groupBy("family", "elision", "station").agg(F.sum("words_ring").alias("words"), F.sum("words_remote").alias("remote"), F.sum("messages").alias("messages"))
    return by_station.groupBy("family", "elision").agg(F.max("words").alias("max_words"), F.avg("words").alias("mean_words"), F.max("messages").alias("messages"), F.sum("remote").alias("remote_words"))


def by_stage(ledger: DataFrame) -> DataFrame:
    """Replication (copy, reduce, fiber values), propagation (passes) and the rest, stage by stage."""
    return ledger.groupBy("family", "elision", "stage").agg(F.max("words_ring").alias("max_words"), F.sum("words_ring").alias("all_words"), F.sum("words_remote").alias("remote_words"))


def balance(s: DataFrame, grid: Grid) -> DataFrame:
    """Nonzeros of the fullest station over those of an average one."""
    counts = place_sparse(s, grid).groupBy("station").agg(F.count(F.lit(1)).alias("nnz"))
    return counts.agg(F.max("nnz").alias("max_nnz"), (F.sum("nnz") / F.lit(grid.p)).alias("mean_nnz"), (F.max("nnz") * F.lit(float(grid.p)) / F.sum("nnz")).alias("ratio"))
