"""Secret-shared relations at three servers: one directory for each party's view."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..functions import shares
from ..model import POS, Relation, rank_col
from ..operators.ranks import attach


def upload(df: DataFrame, cols: list[str], path: str, nonce: str, row: str = POS, strong: bool = True) -> None:
    """Shares the columns (integers; ranks among them, if owners made them) and writes each party's view of them by row."""
    shared = shares.share(df.select(row, *cols), cols, nonce, row, strong)
    for party in range(3):
        shares.party_view(shared, cols, party).write.mode("overwrite").parquet(f"{path}/party={party}")


def view(spark: SparkSession, path: str, party: int) -> DataFrame:
    return spark.read.parquet(f"{path}/party={party}")


def download(spark: SparkSession, path: str, cols: list[str], parties: tuple[int, int] = (0, 1), row: str = POS) -> DataFrame:
    """Opens the columns from any two parties' views."""
    return shares.open_views({p: view(spark, path, p) for p in parties}, cols, row)


def upload_ranked(rel: Relation, path: str, nonce: str) -> list[str]:
    """Owners rank locally, then share data and ranks alike. Returns the shared columns."""
    cols = [c for c in rel.columns if c != POS]
    upload(rel.df, cols, path, nonce)
    return cols


def rank_at_servers(rel: Relation, keys, path: str, nonce: str) -> Relation:
    """Servers sort data that came without ranks once per key, and share the ranks; later queries use them without sorting."""
    ranked = attach(rel, keys, rel.size, method="sort")
    upload(ranked.df, [rank_col(k) for k in ranked.keys], path, nonce)
    return ranked
