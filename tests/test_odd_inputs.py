"""Results on inputs that the round's findings name."""

import math

from lpstream.operators import measures, relational
from pyspark.sql import functions as F


def test_waterfill_ranges_are_one_order(spark):
    """Ranks, tails and caps over ranges equal those of one sorted list, with ties across and within ranges; no window is without a partition over the rows."""
    rows = [(i, float(i * 37 % 50) + 0.01) for i in range(400)] + [(1000, 1e6)]
    n = spark.createDataFrame(rows, "row_id long, norm double").repartition(4)
    order, left, want = sorted(rows, key=lambda r: (-r[1], r[0])), sum(round(r[1] * 100) for r in rows), []
    for k, (i, x) in enumerate(order, 1):
        left -= round(x * 100)
        want.append((i, k, left / 100, x * (20 - k) >= left / 100))
    for parts in (2, 7, 64):
        got = relational.waterfilled(n, parts=parts)
        assert sorted(map(tuple, got.collect())) == sorted(want)
    assert "unboundedfollowing" not in got._jdf.queryExecution().analyzed().toString().lower()
    assert relational.waterfilled(n.limit(0)).count() == 0


def test_recall_of_nothing_is_nan(spark):
    """No heavy row wanted, or none found: the shares are 0/0, as SQL has it, and no error."""
    none, one = spark.createDataFrame([], "row_id long"), spark.createDataFrame([(1,)], "row_id long")
    r = measures.recall(one, none).first()
    assert math.isnan(r.recall) and r.precision == 0 and (r.wanted, r.found) == (0, 1)
    r = measures.recall(none, one).first()
    assert math.isnan(r.precision) and r.recall == 0
