"""How many equal workers to enrol, as column expressions over tables of scenarios."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tilestar.functions.bounds import up


def enrol_large(p: Column, g: Column, c: Column, w: Column) -> Column:
    """Fewest workers whose panels fill the port: P with 2gcP >= g*g*w, at most p."""
    return F.least(p, up(g * w, 2 * c))


def enrol_machine(p: Column, g: Column, q: Column, flop: Column, word: Column) -> Column:
    """The same from the time of a multiply-add and the time of a coefficient on the link."""
    return F.least(p, F.ceil(g * q / 2.0 * flop / word).cast("bigint"))


def enrol_lu(p: Column, g: Column, c: Column, w: Column) -> Column:
    return F.least(p, up(g * w, 3 * c))


def small_side(r: Column, s: Column, c: Column, w: Column, g: Column) -> Column:
    """For a result too small for P full squares: largest side v, at most g, with ceil(v*w/2c) * v*v <= r*s; 0 if none."""
    fits = F.filter(F.sequence(F.lit(1).cast("bigint"), g), lambda v: up(v * w, 2 * c) * v * v <= r * s)
    return F.coalesce(F.array_max(fits), F.lit(0).cast("bigint"))


def whole_root_of_share(r: Column, s: Column, p: Column) -> Column:
    from tilestar.functions.layout import whole_root

    return whole_root(F.floor(r * s / p).cast("bigint"))


def enrol(df: DataFrame) -> DataFrame:
    """df (p, c, w, g, r, s) with p_used, side and case: large, small_c or short of workers."""
    want = up(F.col("g") * F.col("w"), 2 * F.col("c"))
    v = small_side(F.col("r"), F.col("s"), F.col("c"), F.col("w"), F.col("g"))
    df = df.withColumns({"want": want, "v": v}).withColumn("q_small", up(F.col("v") * F.col("w"), 2 * F.col("c")))
    large = (F.col("want") <= F.col("p")) & (F.col("want") * F.col("g") * F.col("g") <= F.col("r") * F.col("s"))
    small = F.col("q_small") <= F.col("p")
    by_area = whole_root_of_share(F.col("r"), F.col("s"), F.col("p"))
    by_port = F.floor(2 * F.col("c") * F.col("p") / F.col("w")).cast("bigint")
    return df.withColumns(
        {
            "case": F.when(large, "large").when(small, "small_c").otherwise("short"),
            "p_used": F.when(large, F.col("want")).when(small, F.col("q_small")).otherwise(F.col("p")),
            "side": F.when(large, F.col("g")).when(small, F.col("v")).otherwise(F.greatest(F.least(by_area, F.col("g"), F.greatest(by_port, F.lit(1))), F.lit(1))),
        }
    ).drop("want", "v", "q_small")
