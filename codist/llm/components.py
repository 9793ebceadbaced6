"""Connected components of a table of links, by joins only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import stored


def components(links: DataFrame) -> DataFrame:
    """(id, label) for each end of a link (a, b): the least id that links lead to.

    Each round points every node to the least of itself and its neighbours and contracts the links to
    what is pointed to, so that nodes and links shrink by the round. Then pointers are followed from the
    last round back. All rounds together read a small multiple of the links.
    """
    edges = stored(_both(links))
    rounds = []
    while True:
        pointers = stored(edges.groupBy("id").agg(F.least(F.min("other"), F.min("id")).alias("label")))
        rounds.append(pointers)
        to = lambda c: pointers.select(F.col("id").alias(c), F.col("label").alias(f"new_{c}"))  # noqa: E731, B023
        moved = edges.where("id < other").join(to("id"), "id").join(to("other"), "other").select(F.col("new_id").alias("a"), F.col("new_other").alias("b"))
        edges = stored(_both(moved))
        if not edges.limit(1).count():
            break
    labels = rounds.pop()
    while rounds:
        before = rounds.pop()
        labels = stored(before.join(labels.select(F.col("id").alias("label"), F.col("label").alias("far")), "label", "left").select("id", F.coalesce("far", "label").alias("label")))
    return labels


def _both(links: DataFrame) -> DataFrame:
    """Distinct links between different nodes, in both directions."""
    held = links.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    return held.select(F.explode(F.array(F.struct(F.col("a").alias("id"), F.col("b").alias("other")), F.struct(F.col("b").alias("id"), F.col("a").alias("other")))).alias("e")).select("e.*")
