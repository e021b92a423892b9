"""The methods in SQL: `register(spark)` adds functions to the session.

* `cell_cap(heights, l)`: the most rows of any value that stay in a cell with these counts (native).
* `cell_eligible(heights, l)`: whether no value has more than a 1/l share (native; true of no rows).
* `cell_trim(heights, l)`: table function (place, kept, moved), step by step in Python; the native cap gives the same.

Defined results: a null array gives null (no rows of the table function); null heights count as 0; l below 2 gives null.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from celldiv.operators import vectors

_ELIGIBLE = "CASE WHEN l >= 2 THEN aggregate(filter(heights, x -> x IS NOT NULL), 0L, (s, x) -> s + x) >= l * coalesce(array_max(heights), 0L) END"
# falling heights; (places seen, rows before, least bound so far)
_CAP = """CASE WHEN l < 2 OR heights IS NULL THEN NULL WHEN size(filter(heights, x -> x > 0)) < l THEN 0L ELSE least(array_max(heights), aggregate(
  reverse(array_sort(filter(heights, x -> x > 0))), named_struct('j', 0, 'rest', aggregate(filter(heights, x -> x > 0), 0L, (s, x) -> s + x), 'cap', CAST(NULL AS BIGINT)),
  (s, x) -> named_struct('j', s.j + 1, 'rest', s.rest - x, 'cap', least(s.cap, CASE WHEN s.j < l THEN s.rest div (l - s.j) END)), s -> s.cap)) END"""


@udtf(returnType="place int, kept long, moved long")
class CellTrim:
    def eval(self, heights: list[int] | None, l: int) -> Iterator[tuple[int, int, int]]:
        if heights is None or l is None or l < 2:
            return
        cell = {i: h for i, h in enumerate(heights) if h}
        vectors.trim([cell], l)
        for i, h in enumerate(heights):
            yield i, cell.get(i, 0), (h or 0) - cell.get(i, 0)


def register(spark: SparkSession) -> None:
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION cell_eligible(heights ARRAY<BIGINT>, l INT) RETURNS BOOLEAN RETURN {_ELIGIBLE}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION cell_cap(heights ARRAY<BIGINT>, l INT) RETURNS BIGINT RETURN {_CAP}")
    spark.udtf.register("cell_trim", CellTrim)
