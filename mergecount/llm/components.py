"""Connected components of a table of links, by rounds of star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C


def _towards_min(links: DataFrame, larger_only: bool, total: int) -> DataFrame:
    """Each node's neighbours (those above it, or those not above it) are linked to the least of its neighbourhood.

    A node's least neighbour comes from an aggregate with partial sums. Nodes with over 1 / HOT of all links
    get it by broadcast (there are HOT of them at most), so their links are never dealt to one task.
    """
    both = links.select("u", "v") if not larger_only else links.select("u", "v").union(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("_n")).select("u", F.least("u", "m").alias("m"), "_n")
    joined = C.join_hot(both, least, "u", total)
    if larger_only:
        return joined.filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v")
    return joined.select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v"))).filter("u <> v")


def connected_components(links: DataFrame, a: str, b: str) -> DataFrame:
    """(node, root): every node that has a link, with the least node that it is connected to.

    Large-star and small-star rounds until nothing changes; the number of rounds grows with the
    logarithm of the number of links. Every half round's table is written to the shared folder,
    and the driver keeps nothing of a round that is over.
    """
    u, v = F.greatest(a, b), F.least(a, b)
    tidy = lambda df: df.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    now = C.materialize(links.select(u.alias("u"), v.alias("v")).filter("u <> v").distinct(), "links")
    total, state = now.count(), None
    while total:
        large = C.materialize(tidy(_towards_min(now, True, 2 * total)), "stars")
        now = C.materialize(tidy(_towards_min(large, False, total)), "links")
        seen = now.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v")), F.sum(F.hash("u", "v").cast("long"))).first()
        if seen == state:
            break
        total, state = seen[0], seen
        C.release(now.sparkSession)
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def with_component(classes: DataFrame, roots: DataFrame) -> DataFrame:
    """(fp, component_id, _n) of classes (fp, least, _n): the least of all classes with one root."""
    rooted = classes.join(roots, F.col("fp") == F.col("node"), "left").select("fp", "least", "_n", F.coalesce("root", "fp").alias("root"))
    rooted = C.materialize(rooted, "rooted")
    of_root = rooted.groupBy("root").agg(F.min("least").alias("component_id"), F.count("*").alias("_m"))
    joined = C.join_hot(rooted, of_root, "root", rooted.count(), "_m")
    return joined.select("fp", "component_id", "_n")
