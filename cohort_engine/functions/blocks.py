"""A table function over blocks of users, for SQL: ``SELECT * FROM cohort_blocks(TABLE(t) PARTITION BY user ORDER BY (time), 'x')``."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="user string, birth_time timestamp_ntz, tuples int, later int")
class CohortBlocks:
    """For each user ``user, birth_time, tuples, later``. Columns are taken as user, time and action, in this order. Slow; for clarity."""

    def __init__(self) -> None:
        self.user, self.birth, self.tuples, self.later = None, None, 0, 0

    def eval(self, row, action: str):
        user, time, act = row[0], row[1], row[2]
        self.user = str(user)
        self.tuples += 1
        if self.birth is None and act == action:
            self.birth = time
        elif self.birth is not None and time > self.birth:
            self.later += 1

    def terminate(self):
        yield self.user, self.birth, self.tuples, self.later


def register(spark: SparkSession) -> None:
    spark.udtf.register("cohort_blocks", CohortBlocks)
