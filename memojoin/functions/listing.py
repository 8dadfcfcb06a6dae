"""Decompositions of a query text as a table function."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="td int, node int, parent int, bag string, adhesion string, owned string")
class Decompositions:
    def eval(self, query: str, max_adhesion: int):
        from memojoin.plans.enumeration import enumerate_tds
        from memojoin.plans.query import parse_cq

        for k, td in enumerate(enumerate_tds(parse_cq(query), max_adhesion)):
            for node, parent, bag, adhesion, owned in td.listing():
                yield k, node, parent, ",".join(bag), ",".join(adhesion), ",".join(owned)


def register(spark: SparkSession, name: str = "decompositions") -> None:
    """For SQL: SELECT * FROM decompositions('E(a,b), E(b,c)', 2), also after LATERAL."""
    spark.udtf.register(name, Decompositions)
