"""Which way to read: touched segments only, or everything."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trieaccess.operators import access as A


@dataclass(frozen=True)
class Choice:
    strategy: str  # "point": filter the store by the few sequences asked for; "kernel": co-locate requests and segments; "expand": decompress all
    reason: str


def choose(n_requests: int, asked_symbols: int, stored_symbols: int, few: int = 1000) -> Choice:
    if asked_symbols * 2 >= stored_symbols:
        return Choice("expand", f"{asked_symbols} of {stored_symbols} symbols are asked for")
    if n_requests <= few:
        return Choice("point", f"{n_requests} requests name their sequences")
    return Choice("kernel", f"{n_requests} requests meet the segments they touch")


def explain_access(heads: DataFrame, requests: DataFrame, few: int = 1000) -> Choice:
    """`heads` has a row a segment with seq_id, seg_no and seq_len: a written store, or segments not compressed yet."""
    asked = requests.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.col("l2") - F.col("l1") + 1), F.lit(0)).alias("s")).first()
    stored = heads.where("seg_no = 0").agg(F.coalesce(F.sum("seq_len"), F.lit(0)).alias("s")).first()
    return choose(asked.n, asked.s, stored.s, few)


def planned_access(store: DataFrame, requests: DataFrame, capacity: int, heads: DataFrame | None = None, few: int = 1000) -> DataFrame:
    """req_id, value by the chosen way. A store that is still a plan rather than files is computed once if `heads` is given."""
    heads = store if heads is None else heads
    how = explain_access(heads, requests, few).strategy
    if how == "expand":
        return A.access_by_full_expand(store, requests, capacity, heads)
    if how == "point":
        ids = [r.seq_id for r in requests.select("seq_id").distinct().collect()]  # at most `few`
        store = store.where(F.col("seq_id").isin(ids))
    return A.access(store, requests, capacity, heads=heads).select("req_id", "value")
