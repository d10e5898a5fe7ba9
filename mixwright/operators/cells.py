"""Cell compression: documents of one cluster and quality level share their weight, so a small table decides all frequencies."""

from __future__ import annotations

from functools import reduce
from operator import and_

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixwright.functions.hashing import uniform
from mixwright.functions.storage import checked, kept

from .sampling import check, minmax, score_frequencies, weight


def build(df: DataFrame, keys: tuple[str, ...] = ("domain", "cluster", "quality")) -> DataFrame:
    """(keys, diversity, n, tokens): one shuffle of at most tasks x cells rows, whatever the corpus."""
    return df.groupBy(*keys).agg(F.min("diversity").alias("diversity"), F.count("*").alias("n"), F.sum("n_tokens").cast("long").alias("tokens"))


def solve(cells: DataFrame, alpha: float = 0.8, tau: float = 0.2, t_tgt: float | None = None, share: float | None = None, budget: str = "documents") -> DataFrame:
    """Append p and c to each cell; ``c`` is per document."""
    return score_frequencies(cells, alpha, tau, t_tgt, share, budget)


def apply(df: DataFrame, solved: DataFrame, keys: tuple[str, ...] = ("domain", "cluster", "quality")) -> DataFrame:
    """Carry p and c back to documents by a broadcast of the cells, if they are counted to be few enough."""
    return df.join(checked(kept(solved.select(*keys, "p", "c"), "cells")), list(keys))


def sweep(cells: DataFrame, grid: DataFrame) -> DataFrame:
    """(grid columns, cell columns, p, c) for all rows of a grid of alpha, tau and share: no pass over documents.

    Cells times grid rows, both small tables.
    """
    scaled = minmax(cells)
    all_rows = scaled.crossJoin(F.broadcast(grid)).withColumn("p", F.col("alpha") * F.col("diversity_01") + (1 - F.col("alpha")) * F.col("quality_01"))
    keys = grid.columns
    tops = all_rows.groupBy(*keys).agg(F.max("p").alias("p_top"))
    with_top = all_rows.join(F.broadcast(tops), keys).withColumn("e", F.exp((F.col("p") - F.col("p_top")) / F.col("tau")))
    sums = with_top.groupBy(*keys).agg(F.sum(F.col("n") * F.col("e")).alias("z_total"), F.sum("n").alias("n_total"))
    return with_top.join(F.broadcast(sums), keys).withColumn("c", F.col("n_total") * F.col("share") * F.col("e") / F.col("z_total")).drop("p_top", "e", "z_total", "n_total")


def sweep_totals(df: DataFrame, swept: DataFrame, grid: list[tuple[float, ...]], names: tuple[str, ...], keys: tuple[str, ...] = ("domain", "cluster", "quality"), seed: int = 42, id_col: str = "doc_id") -> DataFrame:
    """What each row of a grid draws: (names, n_copies, tokens_drawn, min_c, max_c, mean_p, zero_share).

    A cell carries its frequencies over the grid as columns of one row, a document draws once and makes its copies of all of
    them, and sums go by position, so no document is multiplied.
    """
    at = [reduce(and_, (F.col(n) == F.lit(x) for n, x in zip(names, point, strict=True))) for point in grid]
    wide = swept.groupBy(*keys).agg(*[F.max(F.when(s, F.col(c))).alias(f"_{c}{i}") for i, s in enumerate(at) for c in ("p", "c")])
    drawn = df.join(checked(kept(wide, "cells")), list(keys)).withColumn("_u", uniform(id_col, seed))

    def whole(i: int):
        c = F.round(f"_c{i}", 9)
        return F.floor(c) + (F.col("_u") < c - F.floor(c)).cast("long")

    drawn = drawn.select("n_tokens", *[x for i in range(len(grid)) for x in (f"_p{i}", f"_c{i}", whole(i).alias(f"_k{i}"))])
    sums = drawn.agg(*[x.alias(f"{n}_{i}") for i in range(len(grid)) for n, x in (
        ("n_copies", F.sum(f"_k{i}")), ("tokens_drawn", F.sum(F.col("n_tokens") * F.col(f"_k{i}"))), ("min_c", F.min(f"_c{i}")), ("max_c", F.max(f"_c{i}")), ("mean_p", F.avg(f"_p{i}")), ("zero_share", F.avg((F.col(f"_k{i}") == 0).cast("int"))))])
    rows = [F.struct(*[F.lit(x).alias(n) for n, x in zip(names, point, strict=True)], *[F.col(f"{n}_{i}").alias(n) for n in ("n_copies", "tokens_drawn", "min_c", "max_c", "mean_p", "zero_share")]) for i, point in enumerate(grid)]
    return sums.select(F.explode(F.array(*rows)).alias("r")).select("r.*")


def expected_profile(solved: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Expected share of documents at each copy count, without a draw."""
    low, rest = F.floor("c"), F.col("c") - F.floor("c")
    both = F.array(F.struct(low.alias("copies"), (F.col("n") * (1 - rest)).alias("docs")), F.struct((low + 1).alias("copies"), (F.col("n") * rest).alias("docs")))
    out = solved.select(*by, F.explode(both).alias("x")).groupBy(*by, F.col("x.copies").cast("int").alias("copies")).agg(F.sum("x.docs").alias("expected_docs"))
    return out.filter("expected_docs > 0")


def stacked(cells: DataFrame, alpha: float, tau: float) -> DataFrame:
    check(alpha, tau)
    return weight(minmax(cells), alpha)
