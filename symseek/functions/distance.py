"""Distances as column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def edit_distance(a: Column, b: Column) -> Column:
    """Least number of insertions, deletions and substitutions."""
    return F.levenshtein(a, b)


def edit_distance_within(a: Column, b: Column, k: int | Column) -> Column:
    """The edit distance up to k, null above it. k may be a column."""
    if isinstance(k, int):
        return F.nullif(F.levenshtein(a, b, k), F.lit(-1))
    return F.nullif(F.call_function("levenshtein", a, b, k), F.lit(-1))


def symbols(text: Column) -> Column:
    return F.filter(F.split(text, ""), lambda x: x != "")


def dp_last_row(pattern: Column, text: Column) -> Column:
    """Distances of the pattern to every prefix of text (length 0 on), from one matrix of which one column is kept at a time."""
    p = symbols(pattern)
    column0 = F.sequence(F.lit(0), F.size(p))

    def next_column(state: Column, sym: Column) -> Column:
        old = state["column"]
        head = F.array(old[0] + 1)

        def cell(new: Column, j: Column) -> Column:
            best = F.least(F.element_at(new, -1) + 1, old[j] + 1, old[j - 1] + F.when(p[j - 1] == sym, 0).otherwise(1))
            return F.concat(new, F.array(best))

        column = F.when(F.size(p) == 0, head).otherwise(F.aggregate(F.sequence(F.lit(1), F.greatest(F.size(p), F.lit(1))), head, cell))
        return F.struct(column.alias("column"), F.concat(state["row"], F.array(F.element_at(column, -1))).alias("row"))

    start = F.struct(column0.alias("column"), F.array(F.size(p)).alias("row"))
    return F.aggregate(symbols(text), start, next_column, lambda s: s["row"])


def free_start_row(pattern: Column, text: Column) -> Column:
    """As dp_last_row, but a match may begin anywhere: the first cell of every column is zero. One value per symbol of text."""
    p = symbols(pattern)

    def next_column(state: Column, sym: Column) -> Column:
        old = state["column"]
        zero = F.array(F.lit(0))

        def cell(new: Column, j: Column) -> Column:
            best = F.least(F.element_at(new, -1) + 1, old[j] + 1, old[j - 1] + F.when(p[j - 1] == sym, 0).otherwise(1))
            return F.concat(new, F.array(best))

        column = F.aggregate(F.sequence(F.lit(1), F.size(p)), zero, cell)
        return F.struct(column.alias("column"), F.concat(state["row"], F.array(F.element_at(column, -1))).alias("row"))

    start = F.struct(F.sequence(F.lit(0), F.size(p)).alias("column"), F.array().cast("array<int>").alias("row"))
    return F.aggregate(symbols(text), start, next_column, lambda s: s["row"])


def select_band(last_row: Column, lp: Column, k: Column) -> Column:
    """Of a last row (length 0 on), the entries for lengths lp - k (1 at least) to lp + k: a unit built for larger patterns gives more than these."""
    low = F.greatest(lp - k, F.lit(1))
    return F.slice(last_row, low + 1, lp + k - low + 1)


def prefix_distances(text: Column, start: Column, pattern: Column, k: int) -> Column:
    """array<struct<len, dist>> of all band lengths at one start, from a single matrix of width lp + k."""
    lp = F.char_length(pattern)
    low = F.greatest(lp - k, F.lit(1))
    band = select_band(dp_last_row(pattern, F.substr(text, (start + 1).cast("int"), lp + k)), lp, F.lit(k))
    return F.transform(band, lambda d, i: F.struct((low + i).cast("int").alias("len"), d.cast("int").alias("dist")))


def dp_matrix(df: DataFrame, pattern: str, text: str, *keys: str) -> DataFrame:
    """All cells (n, m, c) of the matrix between two columns' strings, for inspection, behind the columns that tell the rows apart."""
    rows = df.select(*keys, F.col(pattern).alias("p"), F.col(text).alias("s"))
    cells = rows.select(*keys, "p", "s", F.explode(F.sequence(F.lit(0), F.char_length("p"))).alias("n")).select(*keys, "p", "s", "n", F.explode(F.sequence(F.lit(0), F.char_length("s"))).alias("m"))
    return cells.select(*keys, "n", "m", F.levenshtein(F.substr("p", F.lit(1), F.col("n")), F.substr("s", F.lit(1), F.col("m"))).alias("c"))


def hamming(a: Column, b: Column) -> Column:
    """Substitutions only; null for unequal lengths."""
    apart = F.zip_with(symbols(a), symbols(b), lambda x, y: F.when(x == y, 0).otherwise(1))
    return F.when(F.char_length(a) == F.char_length(b), F.aggregate(apart, F.lit(0), lambda s, x: s + x))


def indel_distance(a: Column, b: Column) -> Column:
    """Insertions and deletions only: both lengths less twice the longest common subsequence."""
    p = symbols(a)

    def next_column(old: Column, sym: Column) -> Column:
        def cell(new: Column, j: Column) -> Column:
            best = F.when(p[j - 1] == sym, old[j - 1]).otherwise(F.least(F.element_at(new, -1), old[j]) + 1)
            return F.concat(new, F.array(best))

        return F.aggregate(F.sequence(F.lit(1), F.size(p)), F.array(old[0] + 1), cell)

    whole = F.aggregate(symbols(b), F.sequence(F.lit(0), F.size(p)), next_column, lambda c: F.element_at(c, -1))
    return F.when(F.char_length(a) == 0, F.char_length(b)).otherwise(whole)


def episode_distance(pattern: Column, text: Column) -> Column:
    """Insertions only: the symbols to add to pattern to get text; null if pattern isn't a subsequence of it."""
    matched = F.aggregate(symbols(text), F.lit(0), lambda j, sym: j + F.when(F.substr(pattern, j + 1, F.lit(1)) == sym, 1).otherwise(0))
    return F.when(matched == F.char_length(pattern), F.char_length(text) - F.char_length(pattern))
