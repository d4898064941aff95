"""All versions of one identity under a belief state."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..substrate.snapshots import scope


def version_history(versions: DataFrame, ident: str, as_of_tt: int | None = None, audit: bool = False) -> DataFrame:
    """Current belief, belief pinned at ``as_of_tt``, or with ``audit`` every belief ever held."""
    mine = versions.where(F.col("ident") == ident)
    return mine if audit else scope(mine, as_of_tt)
