"""Histories for users who write SQL: a view, a table function on it, and a UDTF on arrays."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="us bigint, event_id bigint")
class ReplayTail:
    """The last n events at or before t of one sequence in arrays."""

    def eval(self, us, event_id, t, n):
        kept = [x for x in zip(us, event_id) if x[0] <= t]
        yield from kept[max(0, len(kept) - n) :]


def register(spark: SparkSession, stripes: DataFrame, name: str = "history") -> None:
    """View `name` (a row for each stripe), function `name`_tail(user, t, n) and UDTF replay_tail(us, event_id, t, n).

    The function drops stripes that begin after t before it opens any.
    """
    stripes.createOrReplaceTempView(name)
    spark.sql(f"""
        CREATE OR REPLACE TEMPORARY FUNCTION {name}_tail(of_user BIGINT, t BIGINT, n INT)
        RETURNS TABLE (us BIGINT, event_id BIGINT)
        RETURN SELECT us, event_id FROM (
          SELECT e.us, e.event_id, row_number() OVER (ORDER BY e.us DESC, e.event_id DESC) AS back
          FROM {name} LATERAL VIEW inline(arrays_zip(us, event_id)) e AS us, event_id
          WHERE user_id = {name}_tail.of_user AND first_us <= {name}_tail.t AND e.us <= {name}_tail.t)
        WHERE back <= {name}_tail.n""")
    spark.udtf.register("replay_tail", ReplayTail)
