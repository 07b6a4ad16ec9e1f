from pyspark.sql import functions as F

from windowjoin.operators import measures, sequence
from windowjoin.predicates import NotEqual
from windowjoin.queries import measures as queries
from windowjoin.queries.base import clicks_views


def test_not_equal_touches_both_sides_of_the_value(spark, sf):
    prepared = sequence.prepare(clicks_views(spark, sf), 500)
    fixed = F.array(*map(F.lit, queries.FIXED)).cast("array<bigint>")
    table = prepared.select("side", "sub_id").distinct().withColumn("splitters", fixed)
    row = measures.comparisons(prepared, NotEqual(), queries.W, queries.LAYOUT, table).first()
    assert row.touched == row.full_scan and row.partitions == 32 * row.asked
