"""The detector over a stream of edges: every micro-batch goes on from the counters, labels and sketch that the last one left.

State is a folder of tables for each batch: state (node, deg, community) and sketch (row_no, cell, cnt). A batch that
runs again writes the same folder again, so failures repeat nothing. The sketch is linear: a node's degree is taken out
of its old community's cells and put into the new one's.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from graphsummary.operators import detect, sketch
from graphsummary.operators.edges import degrees

STATE = "node bigint, deg bigint, community bigint"
SKETCH = "row_no int, cell bigint, cnt bigint"


class Detector:
    """State of a detection over micro-batches of edges (seq, src, dst); seq orders the edges within a batch."""

    def __init__(self, spark: SparkSession, state_dir: str, cap: int, admit: str = "le", tie: str = "source", depth: int = 4, width: int = 1025):
        self.spark, self.dir, self.cap, self.admit, self.tie, self.depth, self.width = spark, state_dir.rstrip("/"), cap, admit, tie, depth, width

    def _path(self, batch: int, name: str) -> str:
        return f"{self.dir}/batch={batch:012d}/{name}"

    def _last(self, before: int | None = None) -> int | None:
        """The latest batch whose sketch, which is written last, is complete."""
        p = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.dir}/batch=*/sketch/_SUCCESS")
        found = p.getFileSystem(self.spark._jsc.hadoopConfiguration()).globStatus(p)
        ids = sorted(int(str(f.getPath().getParent().getParent().getName()).split("=")[1]) for f in found or [])
        ids = [i for i in ids if before is None or i < before]
        return ids[-1] if ids else None

    def state(self, batch: int | None = None) -> DataFrame:
        batch = self._last() if batch is None else batch
        return self.spark.createDataFrame([], STATE) if batch is None else self.spark.read.schema(STATE).parquet(self._path(batch, "state"))

    def sketch(self, batch: int | None = None) -> DataFrame:
        batch = self._last() if batch is None else batch
        return self.spark.createDataFrame([], SKETCH) if batch is None else self.spark.read.schema(SKETCH).parquet(self._path(batch, "sketch"))

    def assignment(self) -> DataFrame:
        return self.state().select("node", "community")

    def step(self, edges: DataFrame, batch: int) -> None:
        """Take one micro-batch."""
        last = self._last(batch)
        old = self.state(last) if last is not None else self.spark.createDataFrame([], STATE)
        labels = detect.stream(edges, self.cap, self.admit, self.tie, labels=old.select("node", "community"), offset=old.select("node", "deg"))
        fresh = degrees(edges).toDF("node", "more")
        new = labels.join(fresh, "node", "left").join(old.toDF("node", "deg", "was"), "node", "left")
        new = new.select("node", (F.coalesce("deg", F.lit(0)) + F.coalesce("more", F.lit(0))).cast("bigint").alias("deg"), "community")
        new.write.mode("overwrite").parquet(self._path(batch, "state"))
        now = self.spark.read.schema(STATE).parquet(self._path(batch, "state"))
        both = now.join(old.toDF("node", "old_deg", "old_community"), "node", "left")
        changed = both.where("old_community is null or old_community <> community or old_deg <> deg")
        moves = changed.select(F.explode(F.array(F.struct(F.col("community").alias("c"), F.col("deg").alias("d")), F.struct(F.col("old_community").alias("c"), (-F.col("old_deg")).alias("d")))).alias("m")).select("m.*").where("c is not null")
        delta = sketch.build(moves, "c", "d", self.depth, self.width)
        before = self.sketch(last) if last is not None else self.spark.createDataFrame([], SKETCH)
        sketch.merge(before, delta).where("cnt <> 0").write.mode("overwrite").parquet(self._path(batch, "sketch"))


def attach(stream: DataFrame, detector: Detector, checkpoint: str, edges: Callable[[DataFrame], DataFrame] | None = None, available_now: bool = True) -> StreamingQuery:
    """Run a detector over a stream; edges turns a micro-batch into (seq, src, dst)."""
    def each(batch: DataFrame, batch_id: int) -> None:
        made = edges(batch) if edges else batch
        if made.limit(1).count():
            detector.step(made, batch_id)

    writer = stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()
