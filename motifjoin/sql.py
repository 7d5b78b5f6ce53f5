"""A text façade: match patterns over views, results as views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from motifjoin.operators.static_join import static_join
from motifjoin.plans.query import JoinQuery, parse_query


def match(spark: SparkSession, text: str, view: str | None = None, **options) -> DataFrame:
    """``match(spark, "tri(a,b,c) := e(a,b), e(a,c), e(b,c), a < b")`` over the views ``e``."""
    query: JoinQuery = parse_query(text)
    out = static_join(query, {a.relation: spark.table(a.relation) for a in query.atoms}, **options)
    out.createOrReplaceTempView(view or query.name)
    return out
