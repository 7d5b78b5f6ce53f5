"""A relation that changes: committed base, signed log, and changes not committed yet.

On storage a relation is a compacted base and a log of normalised signed
changes per version, both under a manifest that is replaced by one atomic
rename (atomic on file systems that have one; an object store needs a committer
of its own); readers trust the manifest alone, so a crash between writing and
committing leaves nothing visible, and committing a version twice changes
nothing. ``as_of`` is the base without what the log deletes, and what it inserts:
logs of changes up to ``BROADCAST_ROWS`` rows are sent to the base's tasks, so that
no version moves the base. Counts per value are stored with the base; a version adds
the log's signs to them.
"""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifjoin.plans.query import clean
from motifjoin.workspace import materialize, new_path

#: Rows of changes, or of prefixes that grow from changes, that may be sent to every task.
BROADCAST_ROWS = 500_000


def sent(df: DataFrame, rows: int) -> DataFrame:
    """A frame of a known number of rows, broadcast within the bound."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def normalize_delta(base: DataFrame, delta: DataFrame, still: bool = False) -> DataFrame:
    """Net effect of ``delta`` (columns of ``base`` and ``w``) on ``base``: rows with w = 1 or -1.

    Several changes of one row add up and count by their sign; inserting what is there
    and deleting what is not are dropped. ``still``: the net changes are stored and, if few,
    sent to the base, which is read once and does not move; else one plan of joins.
    """
    cols = base.columns
    net = delta.na.drop(subset=cols).groupBy(*cols).agg(F.sum("w").alias("w")).filter("w <> 0").withColumn("w", F.signum("w").cast("int"))
    if not still:
        return net.filter("w > 0").join(base, cols, "left_anti").unionByName(net.filter("w < 0").join(base, cols, "left_semi")).select(*cols, "w")
    net = materialize(net, "net")
    here = base.join(sent(net, net.count()), cols).select(*cols, "w")
    here = materialize(here, "here")
    return net.filter("w > 0").join(here, cols, "left_anti").unionByName(here.filter("w < 0")).select(*cols, "w")


def apply_delta(base: DataFrame, delta: DataFrame, rows: int | None = None) -> DataFrame:
    """``base`` after normalised changes, of which there are ``rows``."""
    cols = base.columns
    gone = delta.filter("w < 0").select(*cols)
    return base.join(gone if rows is None else sent(gone, rows), cols, "left_anti").unionByName(delta.filter("w > 0").select(*cols))


class VersionedRelation:
    """The three regions of a changing relation; versions are increasing numbers."""

    def __init__(self, spark: SparkSession, path: str | None = None, compact_share: float = 0.1) -> None:
        self.spark, self.path, self.compact_share = spark, path or new_path(spark, "relation"), compact_share
        self._fs = spark.sparkContext._jvm.org.apache.hadoop.fs
        self._staged: dict[int, DataFrame] = {}
        self._manifest = self._read_manifest()

    # manifest: {"base": path, "base_version": v, "base_rows": n, "counts": [path per column], "log": [[version, path, rows], ...]}
    def _file(self, name: str):
        where = self._fs.Path(f"{self.path}/{name}")
        return where, where.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())

    def _read_manifest(self) -> dict | None:
        where, fs = self._file("manifest.json")
        if not fs.exists(where):
            return None
        return json.loads("".join(r[0] for r in self.spark.read.text(where.toString()).collect()))

    def _write_manifest(self, manifest: dict) -> None:
        part, fs = self._file(f"manifest-{uuid.uuid4().hex}.json")
        out = fs.create(part)
        out.write(bytearray(json.dumps(manifest).encode()))
        out.close()
        target, _ = self._file("manifest.json")
        context = self.spark.sparkContext._jvm.org.apache.hadoop.fs.FileContext.getFileContext(part.toUri(), self.spark.sparkContext._jsc.hadoopConfiguration())
        options = self.spark.sparkContext._gateway.new_array(self.spark.sparkContext._jvm.org.apache.hadoop.fs.Options.Rename, 1)
        options[0] = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Options.Rename.OVERWRITE
        context.rename(part, target, options)
        self._manifest = manifest

    @property
    def rows(self) -> int:
        """Rows of the base."""
        return self._manifest["base_rows"]

    def preload(self, df: DataFrame, version: int = 0) -> None:
        """Start from these rows, without changes."""
        self._write_base(clean(df), version)

    def _write_base(self, df: DataFrame, version: int) -> None:
        path = f"{self.path}/base-{version}-{uuid.uuid4().hex[:8]}"
        df.write.parquet(path)
        base = self.spark.read.parquet(path)
        counts = [f"{path}-counts/{c}" for c in base.columns]
        for c, where in zip(base.columns, counts):
            base.groupBy(c).agg(F.count(F.lit(1)).alias("n")).write.parquet(where)
        self._write_manifest({"base": path, "base_version": version, "base_rows": base.count(), "counts": counts, "log": []})

    @property
    def version(self) -> int:
        if self._manifest is None:
            raise RuntimeError("nothing is loaded")
        log = self._manifest["log"]
        return log[-1][0] if log else self._manifest["base_version"]

    def stage(self, version: int, delta: DataFrame) -> DataFrame:
        """Normalise changes against the last version and hold them, uncommitted, as version ``version``."""
        if version <= self.version:
            raise ValueError(f"version {version} is committed")
        names = [*self.as_of(self.version).columns, "w"]
        path = f"{self.path}/log/ver={version}-{uuid.uuid4().hex[:8]}"
        normalize_delta(self.as_of(self.version), delta.toDF(*names), still=True).write.parquet(path)
        self._staged[version] = self.spark.read.parquet(path)
        self._paths = {**getattr(self, "_paths", {}), version: (path, self._staged[version].count())}
        return self._staged[version]

    def changes(self, version: int) -> DataFrame | None:
        """The normalised changes of a version in the log, committed or staged."""
        if version in self._staged:
            return self._staged[version]
        return next((self.spark.read.parquet(p) for v, p, _ in self._manifest["log"] if v == version), None)

    def commit(self, version: int, compact: bool = True) -> None:
        """Make a staged version visible; a version that is visible already stays as it is."""
        if version <= self.version:
            return
        self._staged.pop(version)
        self._write_manifest({**self._manifest, "log": [*self._manifest["log"], [version, *self._paths[version]]]})
        if compact:
            self.compact_if_long()

    def compact_if_long(self) -> None:
        if sum(n for _, _, n in self._manifest["log"]) > self.compact_share * max(1, self._manifest["base_rows"]):
            self.compact()

    def _logs(self, version: int) -> tuple[DataFrame | None, int]:
        """The net changes from the base to a version, and at most how many."""
        logs = [(self.spark.read.parquet(p), n) for v, p, n in self._manifest["log"] if v <= version and n]
        logs += [(df, self._paths[v][1]) for v, df in sorted(self._staged.items()) if v <= version]
        if len(logs) < 2:
            return logs[0] if logs else (None, 0)
        out = logs[0][0]
        for df, _ in logs[1:]:
            out = out.unionByName(df)
        cols = [c for c in out.columns if c != "w"]
        # each log is normalised against the version before it, so the signs of a row sum up to -1, 0 or 1
        return out.groupBy(*cols).agg(F.sum("w").cast("int").alias("w")).filter("w <> 0"), sum(n for _, n in logs)

    def as_of(self, version: int) -> DataFrame:
        """The rows of a version: not older than the base, committed or staged."""
        if version < self._manifest["base_version"]:
            raise ValueError(f"version {version} is compacted away")
        base = self.spark.read.parquet(self._manifest["base"])
        log, rows = self._logs(version)
        return base if log is None else apply_delta(base, log, rows)

    def counts(self, version: int, key: list[str], keys: DataFrame | None = None) -> DataFrame:
        """Net counts per key, from the base's counts and the log's signs; of some ``keys`` only, if given."""
        base = self.spark.read.parquet(self._manifest["base"])
        if len(key) == 1 and self._manifest.get("counts"):
            rows = self.spark.read.parquet(self._manifest["counts"][base.columns.index(key[0])])
        else:
            rows = base.groupBy(*key).agg(F.count(F.lit(1)).alias("n"))
        log, _ = self._logs(version)
        if log is None:
            return rows if keys is None else rows.join(keys, key)
        rows = rows.unionByName(log.groupBy(*key).agg(F.sum("w").alias("n")))
        rows = rows if keys is None else rows.join(keys, key)
        return rows.groupBy(*key).agg(F.sum("n").alias("n")).filter("n > 0")

    def compact(self) -> None:
        """Fold the committed log into a new base."""
        self._write_base(self.as_of(self.version), self.version)
