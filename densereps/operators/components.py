"""Connected components of an edge table by alternating star contractions.

Each contraction is one min-aggregate (combined before the shuffle) and one equi-join; the lineage is cut
with a reliable checkpoint after every round. Nothing is collected but a count and two sums.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densereps.plans.lineage import cut


def _contract(pairs: DataFrame) -> DataFrame:
    """pairs(u, v): join each row with the least id around u, u included."""
    least = pairs.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return pairs.join(least, "u")


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return _contract(both).filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    seen = _contract(down)
    return (
        seen.select(F.explode(F.array("u", "v")).alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
    )


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 100) -> DataFrame:
    """(id, component) for every id of an edge; component is the least id that can be reached.

    Null ends and loops link nothing: a loop's id is returned as its own component unless other edges join it.
    Repeated edges and an empty table are fine.
    """
    clean = edges.select(F.col(src).cast("long").alias("u"), F.col(dst).cast("long").alias("v")).na.drop()
    links = cut(clean.filter("u <> v").distinct())
    loops = clean.filter("u = v").select("u").distinct()
    before = None
    for _ in range(max_rounds):
        links = cut(_small_star(_large_star(links)))
        now = links.agg(
            F.count(F.lit(1)).alias("n"),
            F.bit_xor(F.xxhash64("u", "v")).alias("x"),
            F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("s"),
        ).first()
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = links.select(F.col("v").alias("id")).distinct()
    inner = links.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(
        roots.select("id", F.col("id").alias("component"))
    )
    alone = loops.select(F.col("u").alias("id")).join(inner.select("id"), "id", "left_anti")
    return inner.unionByName(alone.select("id", F.col("id").alias("component")))
