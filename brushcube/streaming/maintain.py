"""Incremental upkeep of a pre-aggregate from a stream: micro-batches append cells as deltas, reads merge them, compaction retires them."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.clause import Clause
from ..plans import measures
from ..plans.preagg import dimensions
from ..sources.store import _fs
from ..views.spec import ViewSpec


class LiveCells:
    """Cells of one (view, clause shape) kept up to date. Centres are constants, fixed when the cells begin: those given, else the means of the
    first batch that has rows; they are kept beside the cells, so that every session reads them by the same ones."""

    def __init__(self, spark: SparkSession, folder: str, view: ViewSpec, clause: Clause, centres: dict[str, float] | None = None):
        self.spark, self.folder, self.view, self.clause = spark, folder.rstrip("/"), view, clause
        self.dims = dimensions(view, clause)
        self._given, self._plan = centres, None

    # -- centres ----------------------------------------------------------------------------------------------------
    def plan(self, rows: DataFrame | None = None) -> measures.MeasurePlan:
        if self._plan is None:
            self._plan = measures.plan(self.view.aggs, self._centres(rows), measures.Options(avg="sum", centre="constant"))
        return self._plan

    def _centres(self, rows: DataFrame | None) -> dict[str, float]:
        inputs = measures.centred_inputs(self.view.aggs)
        if self._given is not None or not inputs:
            return self._given or {}
        fs, p = _fs(self.spark, f"{self.folder}/centres.json")
        if not fs.exists(p):
            if rows is None:
                raise ValueError("no batch has fixed the centres yet")
            means = self.view.steps(rows).agg(*[F.avg(F.expr(f"CAST({x} AS DOUBLE)")) for x in inputs]).first()
            out = fs.create(p, False)
            out.write(bytearray(json.dumps({x: m if m is not None and abs(m) < 1e300 else 0.0 for x, m in zip(inputs, means)}).encode()))
            out.close()
        stream = fs.open(p)
        try:
            return json.loads(self.spark._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()

    # -- writing ----------------------------------------------------------------------------------------------------
    def cells_of(self, rows: DataFrame) -> DataFrame:
        return self.view.steps(rows).groupBy(*[F.expr(s).alias(a) for a, s in self.dims]).agg(*self.plan(rows).create.values())

    def write_batch(self, rows: DataFrame, batch_id: int) -> None:
        """A batch's cells under its id: a batch that is run again replaces itself. Nothing is written for a batch without rows."""
        if not rows.isEmpty():
            self.cells_of(rows).write.mode("overwrite").parquet(f"{self.folder}/deltas/{batch_id}")

    def start(self, stream: DataFrame, once: bool = True):
        return self._begin(stream.writeStream.foreachBatch(self.write_batch), once)

    def _begin(self, writer, once: bool):
        writer = writer.option("checkpointLocation", f"{self.folder}/progress")
        return (writer.trigger(availableNow=True) if once else writer).start()

    # -- reading ----------------------------------------------------------------------------------------------------
    def _finished(self, kind: str) -> list[int]:
        """Numbers of the folders of a kind that were written to their end."""
        fs, p = _fs(self.spark, f"{self.folder}/{kind}")
        names = [s.getPath().getName() for s in fs.listStatus(p)] if fs.exists(p) else []
        return sorted(int(n) for n in names if n.isdigit() and fs.exists(_fs(self.spark, f"{self.folder}/{kind}/{n}/_SUCCESS")[1]))

    def parts(self) -> tuple[DataFrame, int]:
        """(the newest generation's cells and the deltas after it, with the ``batch`` of each; the last batch)."""
        bases = self._finished("bases")
        upto = bases[-1] if bases else -1
        found = [("bases", upto)] if bases else []
        found += [("deltas", n) for n in self._finished("deltas") if n > upto]
        if not found:
            raise ValueError("no batch was written yet")
        out = None
        for kind, n in found:
            one = self.spark.read.parquet(f"{self.folder}/{kind}/{n}").withColumn("batch", F.lit(n))
            out = one if out is None else out.unionByName(one)
        return out, found[-1][1]

    def merged(self) -> DataFrame:
        """All parts merged into cells."""
        cells, _ = self.parts()
        return self._merge(cells)

    def _merge(self, cells: DataFrame) -> DataFrame:
        return cells.groupBy(*[a for a, _ in self.dims]).agg(*self.plan().merge.values())

    def compact(self) -> int:
        """Merge everything written so far into a generation, named by its last batch and published by rename: readers take the newest generation and the
        deltas after it, so nothing counts twice. What the generation before had replaced goes now; what this one replaces stays until the next, for
        readers under way. Returns the last batch."""
        before = self._finished("bases")
        cells, last = self.parts()
        if before and before[-1] == last:
            return last
        aside = f"{self.folder}/.base-{last}"
        self._merge(cells).write.mode("overwrite").parquet(aside)
        fs, src = _fs(self.spark, aside)
        fs.mkdirs(_fs(self.spark, f"{self.folder}/bases")[1])
        if not fs.rename(src, _fs(self.spark, f"{self.folder}/bases/{last}")[1]):
            raise OSError(f"generation {last} could not be published")
        for kind, old in [("bases", n) for n in before[:-1]] + [("deltas", n) for n in self._finished("deltas") if before and n <= before[-1]]:
            fs.delete(_fs(self.spark, f"{self.folder}/{kind}/{old}")[1], True)
        return last

    def answer(self, clause: Clause) -> DataFrame:
        cells = self.merged()
        active = [a for a, _ in self.dims[len(self.view.group):]]
        if not clause.cleared:
            cells = cells.where(clause.bin_predicate(active).column())
        merged = cells.groupBy(*[a for a, _ in self.view.group]).agg(*self.plan().merge.values())
        return self.view.after(merged.select(*[a for a, _ in self.view.group], *self.plan().read.values()))


class StateCells(LiveCells):
    """The same cells as state of the stream: every batch writes the cells that it changed, whole, and of a cell the newest version holds. The state is as large
    as the occupied cells (for many, let the session name a state store on disk). Centres must be given where squares are summed."""

    def start(self, stream: DataFrame, once: bool = True):
        if self._given is None and measures.centred_inputs(self.view.aggs):
            raise ValueError("cells in state need given centres")
        return self._begin(self.cells_of(stream).writeStream.outputMode("update").foreachBatch(self._changed), once)

    def _changed(self, cells: DataFrame, batch_id: int) -> None:
        if not cells.isEmpty():
            cells.write.mode("overwrite").parquet(f"{self.folder}/deltas/{batch_id}")

    def _merge(self, cells: DataFrame) -> DataFrame:
        stats = [c for c in cells.columns if c != "batch" and c not in dict(self.dims)]
        newest = cells.groupBy(*[a for a, _ in self.dims]).agg(F.max_by(F.struct(*stats), "batch").alias("s"))
        return newest.select(*[a for a, _ in self.dims], "s.*")
