"""Result pages: bounded, ordered, with completeness and a digest. Later pages start after the last key, never by an offset."""

from __future__ import annotations

import base64
import hashlib
import json
import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.canon import BELIEF_COLUMNS, DIGITS

DEFAULT_LIMIT = 100


@dataclass
class ResultPage:
    rows: list[dict]
    rows_total: int
    complete: bool
    cursor: str | None
    result_digest: str
    fields: tuple[str, ...] = field(default_factory=tuple)

    @property
    def rows_returned(self) -> int:
        return len(self.rows)


def canonical(value):
    """Plain JSON values with canonical numbers and ordered keys."""
    if isinstance(value, float):
        if math.isnan(value):
            return None
        value = round(value, DIGITS)
        return 0.0 if value == 0 else value
    if isinstance(value, dict):
        return {k: canonical(value[k]) for k in sorted(value)}
    if isinstance(value, (list, tuple)):
        return [canonical(v) for v in value]
    return value


def canonical_json(value) -> str:
    return json.dumps(canonical(value), sort_keys=True, separators=(",", ":"), default=str)


def digest_rows(rows: list[dict]) -> str:
    public = [{k: v for k, v in r.items() if k not in BELIEF_COLUMNS} for r in rows]
    return hashlib.sha256("\n".join(canonical_json(r) for r in public).encode()).hexdigest()


def _encode(key: list) -> str:
    return base64.urlsafe_b64encode(canonical_json(key).encode()).decode()


def _after(order: list[str], key: list) -> Column:
    """Rows whose sort key exceeds ``key``, column by column."""
    test = F.lit(False)
    for i in reversed(range(len(order))):
        c, v = F.col(order[i]), F.lit(key[i])
        test = (c > v) | ((c == v) & test) if i < len(order) - 1 else c > v
    return test


def page(df: DataFrame, order: list[str], limit: int = DEFAULT_LIMIT, cursor: str | None = None) -> ResultPage:
    """One page of ``df`` in the total order of ``order``; nulls sort first and are not paged past, so keys must not be null."""
    held = df.persist()
    try:
        total = held.count()
        rest = held if cursor is None else held.where(_after(order, json.loads(base64.urlsafe_b64decode(cursor))))
        rows = [r.asDict(recursive=True) for r in rest.orderBy(*order).limit(limit + 1).collect()]
    finally:
        held.unpersist()
    more = len(rows) > limit
    rows = rows[:limit]
    after = _encode([rows[-1][c] for c in order]) if more and order else None
    return ResultPage(rows, total, len(rows) == total, after, digest_rows(rows), tuple(df.columns))
