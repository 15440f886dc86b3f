"""Which form of a method suits a table: decided from counts of rows and bytes, never from names or paths."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import graph, sampler

#: Pairs that all-pairs divergences may form; beyond it candidates come first.
MOST_PAIRS = 200_000_000
#: Rows of a few numbers and short strings that a broadcast may hold; the driver and every executor keep them all.
BROADCAST_ROWS = 1_000_000


@dataclass(frozen=True)
class Plan:
    pairs: str  # all or candidates
    chain: str  # local or distributed
    shared_pairs: int  # rows that the all-pairs join would make
    chain_bytes: int


def plan(resp: DataFrame, neighbours: int = 6, most_pairs: int = MOST_PAIRS) -> Plan:
    """The joins of all pairs make one row for each shared word: the sum of squared item counts of the words."""
    per = resp.groupBy("feat").agg(F.count(F.lit(1)).alias("d"))
    rows, pairs = per.agg(F.coalesce(F.sum("d"), F.lit(0)), F.coalesce(F.sum(F.col("d") * (F.col("d") - 1) / 2), F.lit(0.0))).first()
    items = resp.select("item_id").distinct().count()
    size = 12 * rows + 24 * neighbours * items + 8 * items
    return Plan("all" if pairs <= most_pairs else "candidates", "local" if size <= sampler.LOCAL_BYTES else "distributed", int(pairs), int(size))


def broadcasts(side: DataFrame, most_rows: int = BROADCAST_ROWS) -> bool:
    """Whether one side of a join is small enough to be sent to every executor."""
    return side.count() <= most_rows


def divergences(resp: DataFrame, dims: int, eps: float = 1e-2, most_pairs: int = MOST_PAIRS) -> DataFrame:
    """s, t, j of all pairs that share a word, or of candidate pairs if all would be too many."""
    if plan(resp, most_pairs=most_pairs).pairs == "all":
        return graph.symmetric_kl(resp, dims, eps)
    return graph.pair_divergences(resp, graph.candidate_pairs(resp), dims, eps)
