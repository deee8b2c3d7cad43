"""Limit queries: the first frames of a ranking that keep a distance."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F


def spaced(ranked: DataFrame, count: int, distance: int) -> list[int]:
    """Walk a ranking (column ``at`` first) and take frames at least ``distance`` apart until ``count`` are found.

    Every frame taken rules out fewer than 2 * distance others, so the first count * 2 * distance rows decide: a top-k
    of a bounded size, never a full sort.
    """
    out: list[int] = []
    for row in ranked.limit(count * 2 * distance).collect():
        if all(abs(row[0] - x) >= distance for x in out):
            out.append(row[0])
            if len(out) == count:
                break
    return out


def ranked_pages(rows: DataFrame, score: str, at: str, page: int = 2000) -> Iterator[Row]:
    """Rows from the greatest score down (ties: smallest ``at``), ``page`` of them at a time.

    A page is a top-k below the last row of the one before, so the driver never holds more than a page and nothing is sorted as a whole; a walk that stops
    early asks for no more. ``at`` is unique.
    """
    rows = rows.cache()
    try:
        rest = rows
        while True:
            got = rest.orderBy(F.desc(score), at).limit(page).collect()
            yield from got
            if len(got) < page:
                return
            last = got[-1]
            rest = rows.where((F.col(score) < F.lit(last[score])) | ((F.col(score) == F.lit(last[score])) & (F.col(at) > F.lit(last[at]))))
    finally:
        rows.unpersist()
