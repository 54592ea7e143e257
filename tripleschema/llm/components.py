"""Connected components of a link table, by contraction to stars; no link ever leaves the cluster."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tripleschema.llm.common import HOT_ROWS, relieve, removed, spread_join, written


def _met(links: DataFrame, least: DataFrame, n_links: int, hot_rows: int, used: list[DataFrame]) -> DataFrame:
    """``links`` (a, b) with the ``m`` of their ``a`` in ``least`` (a, m, n); n: the links of a."""
    if n_links <= hot_rows:  # no node can have more
        return links.join(least.drop("n"), "a")
    used.append(written(least, "least", n_links))
    return spread_join(links, used[-1], ["a"], "n", hot_rows)


def connected_components(links: DataFrame, max_rounds: int = 100, hot_rows: int = HOT_ROWS) -> DataFrame:
    """``node, label`` of all nodes of links ``(a long, b long)``: the label is the least node that can be reached.

    Rounds of two steps: larger neighbours move to a node's least neighbour, then smaller ones do, until all components
    are stars.  The minimum is aggregated before the shuffle; nodes with over ``hot_rows`` links are joined where their
    links are, so a component or hub of any size is spread over tasks.  Each step is written to the shared folder, which
    cuts the lineage; what the next one has read is deleted.  Self-links and links with a null end are ignored, repeated
    links count once; no links give no rows.
    """
    links = links.select("a", "b").where("a != b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    links, seen = written(links, "links"), None
    for _ in range(max_rounds):
        now = links.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == seen or not now[0]:
            break
        relieve(links.sparkSession, collect=True)  # the plans of the rounds before are garbage that else lets the driver's heap grow
        seen, used = now, [links]
        both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n")).select("a", F.least("a", "m").alias("m"), "n")
        large = _met(both, least, 2 * now[0], hot_rows, used).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a != b").distinct()
        if now[0] > hot_rows:
            used.append(large := written(large, "links", 2 * now[0]))
        small = large.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n"))
        moved = _met(large, small, 2 * now[0], hot_rows, used).select(F.greatest("b", "m").alias("x"), F.least("b", "m").alias("m")).where("x != m")
        links = moved.unionByName(small.select(F.col("a").alias("x"), "m")).select(F.col("x").alias("a"), F.col("m").alias("b")).distinct()
        links = written(links, "links", now[0])
        removed(*used)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return links.select(F.col("a").alias("node"), F.col("b").alias("label")).unionByName(links.select(F.col("b").alias("node"), F.col("b").alias("label")).distinct())
