"""Table function that lists the elements of a rendered feature."""

from __future__ import annotations

import re
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

STEP = re.compile(r"-\[(.*?)\]-> (.*?)(?= -\[|$)", re.S)


@udtf(returnType="pos int, predicate string, element string")
class ExplainFeature:
    def eval(self, feature: str) -> Iterator[tuple[int, str, str]]:
        for i, m in enumerate(STEP.finditer(feature or "")):
            yield i + 1, m[1], m[2]


def register(spark: SparkSession) -> None:
    """explain_feature(text) for SQL."""
    spark.udtf.register("explain_feature", ExplainFeature)
