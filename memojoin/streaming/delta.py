"""Counts kept up to date as edges arrive in batches."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession

from memojoin.operators.catalog import Catalog
from memojoin.operators.frontier import memo_count
from memojoin.plans.decomp import OrderedTD
from memojoin.plans.query import Atom, ConjunctiveQuery


class DeltaCounter:
    """The count of a query over one growing relation.

    A batch adds, for each atom, the results that take a new tuple there, new or old ones before it and only old
    ones behind it; each such term is a memoised count. State (the relation, and the count after each batch) lies
    in Parquet under a shared folder, each batch in a folder of its own: a batch that comes again is answered from
    what was written, so the counter can stand behind foreachBatch.
    """

    def __init__(self, spark: SparkSession, query: ConjunctiveQuery, td: OrderedTD, relation: str, folder: str):
        self.spark, self.query, self.td, self.relation, self.folder = spark, query, td, relation, folder.rstrip("/")

    def _rows(self, batch: int, schema):
        return self.spark.read.schema(schema).parquet(f"{self.folder}/edges/batch={batch}")

    def _log(self) -> dict[int, int]:
        try:
            return {r["batch"]: r["cnt"] for r in self.spark.read.schema("batch long, cnt long").json(f"{self.folder}/counts").collect()}
        except Exception as e:  # the folder does not exist before the first batch
            if "PATH_NOT_FOUND" not in str(e):
                raise
            return {}

    def on_batch(self, batch: DataFrame, batch_id: int) -> int:
        done = self._log()
        if batch_id in done:
            return done[batch_id]
        schema = batch.schema
        # one scan over all folders, whatever the number of past batches
        old = self.spark.read.schema(schema).parquet(*[f"{self.folder}/edges/batch={b}" for b in sorted(done)]) if done else None
        fresh = batch.dropna().distinct()
        fresh = fresh.join(old, batch.columns, "left_anti") if old is not None else fresh
        fresh.write.mode("overwrite").parquet(f"{self.folder}/edges/batch={batch_id}")
        new = self._rows(batch_id, schema)
        old = old if old is not None else new.limit(0)
        every, total = old.unionByName(new), done[max(done)] if done else 0
        at = [k for k, a in enumerate(self.query.atoms) if a.relation == self.relation]
        for k in at:
            atoms = [Atom("__new" if j == k else "__all" if j < k else "__old", a.terms) if j in at else a for j, a in enumerate(self.query.atoms)]
            catalog = Catalog({"__new": new, "__all": every, "__old": old})
            total += memo_count(ConjunctiveQuery(atoms), catalog, self.td).first()["cnt"]
        row = self.spark.createDataFrame([(batch_id, total)], "batch long, cnt long")
        row.coalesce(1).write.mode("append").json(f"{self.folder}/counts")
        return total

    def count(self) -> int:
        done = self._log()
        return done[max(done)] if done else 0

    def describe(self) -> str:
        return json.dumps({"relation": self.relation, "batches": len(self._log()), "count": self.count()})
