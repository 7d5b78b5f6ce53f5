"""Extension indices: bound values to the set of next values, as DataFrames.

An index has up to four forms, all keyed by ``__k0..``: ``members`` (one row per
value, checked by semi-join and enumerated by join), ``counts``, ``lists``
(values as sorted arrays in chunks), and ``resolver`` (values numbered from 1,
so that any range of them can be fetched by equi-join and spread evenly).
"""

from __future__ import annotations

import json
from collections.abc import Mapping, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from motifjoin.operators.versions import VersionedRelation
from motifjoin.plans.stages import Stage
from motifjoin.workspace import materialize

#: Values per chunk of a list; salts that a key is numbered in.
LIST_CHUNK, SALTS = 65_536, 32


class ExtensionIndex:
    """One index of a relation: from the columns ``key_pos`` to the column ``ext_pos``."""

    def __init__(self, relation: DataFrame, key_pos: tuple[int, ...], ext_pos: int) -> None:
        self.keys = [f"__k{i}" for i in range(len(key_pos))]
        self.n_columns = len(relation.columns)
        cols = [F.col(f"c{p}").alias(k) for k, p in zip(self.keys, key_pos)]
        rows = relation.select(*cols, F.col(f"c{ext_pos}").alias("__ext"))
        whole = len(key_pos) + 1 == self.n_columns and ext_pos not in key_pos
        self.members = rows if whole else rows.dropDuplicates()
        self._counts: DataFrame | None = None
        self._resolver: DataFrame | None = None

    def cut(self) -> None:
        """Compute members, counts and resolver once and store them: for jobs that read them many times."""
        self.members = materialize(self.members, "members")
        self._counts = materialize(self.counts, "counts")
        self._resolver = materialize(self.resolver, "resolver")

    @property
    def counts(self) -> DataFrame:
        if self._counts is None:
            self._counts = self.members.groupBy(*self.keys).agg(F.count(F.lit(1)).alias("__cnt")) if self.keys else self.members.agg(F.count(F.lit(1)).alias("__cnt"))
        return self._counts

    def counts_of(self, keys: DataFrame) -> DataFrame:
        """Counts of some distinct keys only; sent to every task, they spare the index a shuffle."""
        return self.members.join(keys, self.keys).groupBy(*self.keys).agg(F.count(F.lit(1)).alias("__cnt"))

    @property
    def lists(self) -> DataFrame:
        """``__k0.., __chunk, __exts``: sorted arrays; a hub's list is cut by ranges of its values' hash."""
        n = self.counts.withColumn("__chunks", F.ceil(F.col("__cnt") / LIST_CHUNK)).select(*self.keys, "__chunks")
        rows = self.members.join(n, self.keys) if self.keys else self.members.crossJoin(n)
        rows = rows.withColumn("__chunk", F.pmod(F.xxhash64("__ext"), F.col("__chunks")).cast("int"))
        return rows.groupBy(*self.keys, "__chunk").agg(F.array_sort(F.collect_list("__ext")).alias("__exts"))

    @property
    def resolver(self) -> DataFrame:
        """``__k0.., __no, __ext``: values numbered in two levels, so that no hub is numbered in one task."""
        if self._resolver is not None:
            return self._resolver
        salted = self.members.withColumn("__salt", F.pmod(F.xxhash64("__ext"), F.lit(SALTS)).cast("int"))
        local = salted.withColumn("__no", F.row_number().over(Window.partitionBy(*self.keys, "__salt").orderBy("__ext")))
        per = salted.groupBy(*self.keys, "__salt").agg(F.count(F.lit(1)).alias("__n"))
        before = Window.partitionBy(*self.keys).orderBy("__salt").rowsBetween(Window.unboundedPreceding, -1)
        offsets = per.withColumn("__before", F.coalesce(F.sum("__n").over(before), F.lit(0))).drop("__n")
        return local.join(offsets, [*self.keys, "__salt"]).select(*self.keys, (F.col("__no") + F.col("__before")).cast("long").alias("__no"), "__ext")

    def bitmaps(self) -> DataFrame:
        """``__k0.., page, bits``: dense non-negative values as bit vectors of 32768 per page."""
        rows = self.members.withColumn("page", F.shiftright("__ext", 15))
        return rows.groupBy(*self.keys, "page").agg(F.expr("bitmap_construct_agg(__ext & 32767)").alias("bits"))


class VersionedIndex(ExtensionIndex):
    """An index of a version of a changing relation: members as base and log, counts from the store's net counts."""

    def __init__(self, store: VersionedRelation, version: int, key_pos: tuple[int, ...], ext_pos: int) -> None:
        super().__init__(store.as_of(version), key_pos, ext_pos)
        self.store, self.version = store, version
        self.column = f"c{key_pos[0]}" if len(key_pos) == 1 and self.n_columns == 2 and ext_pos not in key_pos else None

    @property
    def counts(self) -> DataFrame:
        if self._counts is None and self.column:
            self._counts = self.store.counts(self.version, [self.column]).toDF("__k0", "__cnt")
        return super().counts

    def counts_of(self, keys: DataFrame) -> DataFrame:
        if not self.column:
            return super().counts_of(keys)
        return self.store.counts(self.version, [self.column], keys.withColumnRenamed("__k0", self.column)).toDF("__k0", "__cnt")


class IndexCatalog:
    """Relations by (name, version) and their indices, each built once for any number of atoms.

    ``views`` names the versions of changing relations: (name, version) to (store, number).
    """

    def __init__(self, relations: Mapping[str, DataFrame] | Mapping[tuple[str, str], DataFrame], cut: bool = False, views: Mapping[tuple[str, str], tuple[VersionedRelation, int]] | None = None) -> None:
        self.views = dict(views or {})
        self.relations = {k: store.as_of(v) for k, (store, v) in self.views.items()}
        self.relations |= {k if isinstance(k, tuple) else (k, "new"): df for k, df in relations.items()}
        if cut:  # the relations are computed once, and stored reliably
            self.relations = {k: materialize(df, "relation") for k, df in self.relations.items()}
        self._indices: dict[tuple, ExtensionIndex] = {}

    def relation(self, name: str, version: str = "new") -> DataFrame:
        return self.relations[name, version]

    def get(self, index_id: tuple[str, str, tuple[int, ...], int]) -> ExtensionIndex:
        if index_id not in self._indices:
            relation, version, key_pos, ext_pos = index_id
            view = self.views.get((relation, version))
            self._indices[index_id] = VersionedIndex(*view, key_pos, ext_pos) if view else ExtensionIndex(self.relations[relation, version], key_pos, ext_pos)
        return self._indices[index_id]

    def cut(self, stages: Sequence[Stage]) -> None:
        """Store all forms of the indices that some stages use."""
        for index_id in dict.fromkeys(u.index_id for s in stages for u in s.uses):
            self.get(index_id).cut()

    def __len__(self) -> int:
        return len(self._indices)

    def rows(self) -> int:
        """Index tuples held in all."""
        return sum(i.members.count() for i in self._indices.values())

    def save(self, path: str, buckets: int | None = None) -> None:
        """Store the relations, and each index partitioned by its key and sorted, for later jobs."""
        for (name, version), df in self.relations.items():
            df.write.mode("overwrite").parquet(f"{path}/relation={name}/version={version}")
        for (name, version, key_pos, ext_pos), index in self._indices.items():
            rows = index.members.repartition(*([buckets] if buckets else []), *index.keys) if index.keys else index.members
            where = f"{path}/index/{name}-{version}-{'_'.join(map(str, key_pos))}-{ext_pos}"
            rows.sortWithinPartitions(*index.keys, "__ext").write.mode("overwrite").parquet(where)
        names = json.dumps([[n, v] for n, v in self.relations])
        next(iter(self.relations.values())).sparkSession.createDataFrame([(names, json.dumps([list(k) for k in self._indices]))], "relations string, indices string").coalesce(1).write.mode("overwrite").json(f"{path}/catalog")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> IndexCatalog:
        """A stored catalog: nothing is rebuilt."""
        row = spark.read.schema("relations string, indices string").json(f"{path}/catalog").first()
        out = cls({(n, v): spark.read.parquet(f"{path}/relation={n}/version={v}") for n, v in json.loads(row["relations"])})
        for name, version, key_pos, ext_pos in json.loads(row["indices"]):
            index = out.get((name, version, tuple(key_pos), ext_pos))
            index.members = spark.read.parquet(f"{path}/index/{name}-{version}-{'_'.join(map(str, key_pos))}-{ext_pos}")
        return out


def save_bucketed(members: DataFrame, table: str, keys: list[str], buckets: int = 64) -> None:
    """An index as a bucketed and sorted table: later joins on its key need no exchange of it."""
    members.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys, "__ext").saveAsTable(table)


def build_index(df: DataFrame, key: list[str], ext: str) -> ExtensionIndex:
    """An index of one table by column names."""
    return ExtensionIndex(df.select(*[F.col(k).alias(f"c{i}") for i, k in enumerate(key)], F.col(ext).alias(f"c{len(key)}")).dropDuplicates(), tuple(range(len(key))), len(key))
