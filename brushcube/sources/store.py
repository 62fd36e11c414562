"""Base relations and stored pre-aggregates: snapshots, names by content hash, atomic publishing."""

from __future__ import annotations

import hashlib
import json
import tempfile
import threading
import time
import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; ``sales_wide`` is the named view of line items with their order and customer."""
    if name != "sales_wide":
        return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")
    li, o, c = (load(spark, sf_dir, t) for t in ("lineitem", "orders", "customer"))
    # no hints: Spark broadcasts what its statistics prove small and sorts the rest
    return li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey)


#: The same view for the oracle.
SALES_WIDE = "(SELECT * FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey)"


@dataclass(frozen=True)
class Relation:
    name: str
    df: DataFrame
    snapshot: str


def _fs(spark: SparkSession, path: str):
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()), p


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, else, where both are one process, a new local one."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found and spark.sparkContext.master.split("[")[0] == "local":
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="brushcube-"))
        found = spark.sparkContext.getCheckpointDir()
    if not found:
        raise ValueError("spark.checkpoint.dir names no shared folder")
    return found.rstrip("/")


def _leaves(plan) -> list[str]:
    found, it = [], plan.collectLeaves().iterator()
    while it.hasNext():
        found.append(it.next().getClass().getSimpleName())
    return found


def snapshot_of(df: DataFrame) -> str:
    """Changes when the relation does: its analysed plan, and names, sizes and times of its files, asked of the file system that holds them.
    What a plan's text doesn't tell (data of the session, Python functions) is never taken for equal: such a frame gets a name of its own."""
    spark = df.sparkSession
    plan = df._jdf.queryExecution().analyzed().canonicalized()
    text = plan.treeString(True, False, 2**31 - 1, False, False)  # all fields of every node
    files, seen = sorted(df.inputFiles()), []
    if any(x not in ("LogicalRelation", "HiveTableRelation", "Range", "OneRowRelation") for x in _leaves(plan)) or "python" in text.lower() or "pandas" in text.lower():
        return "frame-" + uuid.uuid4().hex[:16]
    if not files:
        return "plan-" + hashlib.sha256(text.encode()).hexdigest()[:16]
    for folder in sorted({f.rpartition("/")[0] for f in files}):
        fs, p = _fs(spark, folder.replace("%20", " "))
        for s in fs.listStatus(p):
            seen.append((s.getPath().toString(), s.getLen(), s.getModificationTime()))
    wanted = {f.rpartition("/")[2] for f in files}
    facts = [text, *sorted(x for x in seen if x[0].rpartition("/")[2] in wanted)]
    return hashlib.sha256(json.dumps(facts).encode()).hexdigest()[:16]


class Relations:
    """Named base relations of a session."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self._known: dict[str, Relation] = {}

    def add(self, name: str, df: DataFrame, snapshot: str | None = None) -> Relation:
        self._known[name] = r = Relation(name, df, snapshot or snapshot_of(df))
        return r

    def get(self, name: str) -> Relation:
        if name not in self._known:
            self.add(name, self.spark.table(name))
        return self._known[name]


class Store:
    """Pre-aggregates as Parquet folders named by the hash of their definition; other sessions find them by the same name."""

    def __init__(self, spark: SparkSession, root: str | None = None):
        self.spark = spark
        root = root or shared_root(spark)
        self.root = f"{root.rstrip('/')}/cells"
        self.builds = self.hits = 0
        self._locks: dict[str, threading.Lock] = {}
        self._guard = threading.Lock()

    @staticmethod
    def fingerprint(definition: dict) -> str:
        return hashlib.sha256(json.dumps(definition, sort_keys=True).encode()).hexdigest()[:24]

    def lock(self, name: str) -> threading.Lock:
        with self._guard:
            return self._locks.setdefault(name, threading.Lock())

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def exists(self, name: str) -> bool:
        fs, p = _fs(self.spark, f"{self.path(name)}/_SUCCESS")
        return fs.exists(p)

    def publish(self, name: str, df: DataFrame, facts: dict) -> DataFrame:
        """Write aside, then rename; whoever comes second drops their copy."""
        began = time.time()
        aside = f"{self.root}/.building-{name}-{uuid.uuid4().hex}"
        df.write.parquet(aside)
        fs, src = _fs(self.spark, aside)
        dst = _fs(self.spark, self.path(name))[1]
        facts = facts | {"build_ms": round(1000 * (time.time() - began), 1)}
        with_facts = fs.create(_fs(self.spark, f"{aside}/_facts.json")[1])
        with_facts.write(bytearray(json.dumps(facts).encode()))
        with_facts.close()
        if fs.exists(dst) or not fs.rename(src, dst):
            fs.delete(src, True)
        self.builds += 1
        return self.read(name, df.schema)

    def read(self, name: str, schema=None) -> DataFrame:
        r = self.spark.read
        return (r.schema(schema) if schema is not None else r).parquet(self.path(name))

    def facts(self, name: str) -> dict:
        fs, p = _fs(self.spark, f"{self.path(name)}/_facts.json")
        stream = fs.open(p)
        try:
            return json.loads(self.spark._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()

    def list(self) -> list[str]:
        fs, p = _fs(self.spark, self.root)
        return sorted(s.getPath().getName() for s in fs.listStatus(p) if not s.getPath().getName().startswith(".")) if fs.exists(p) else []

    def size_bytes(self, name: str) -> int:
        fs, p = _fs(self.spark, self.path(name))
        return fs.getContentSummary(p).getLength()

    def drop(self, name: str) -> None:
        fs, p = _fs(self.spark, self.path(name))
        fs.delete(p, True)
