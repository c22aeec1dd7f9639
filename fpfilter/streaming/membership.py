"""Filters on streams: probing a frozen filter, online insertion with first-seen output, and exact counterparts."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fpfilter.operators.filters import build_filter, contains, insert_into
from fpfilter.operators.signature import with_signature
from fpfilter.operators.spec import FilterSpec
from fpfilter.sources.tables import FILTER_SCHEMA, save_filter


def probe_stream(stream: DataFrame, key: Column | str, table: DataFrame, to: str = "hit") -> DataFrame:
    """A stream with its answers from a frozen filter of bounded size: stateless, any output mode."""
    return contains(stream, key, table, strategy="broadcast", to=to)


class OnlineFilter:
    """A filter that grows with a stream and lets each key through once.

    Every micro-batch reads the version that its number implies, probes it, passes on one row for each entry that is
    new, and writes the next version; a batch that is run again writes the same version again, so restarts neither
    lose nor double an entry. A false positive may hold a new key back (at about the filter's rate); no key passes
    twice. With ``exact``, columns that tell keys apart, none is held back: rows that the filter finds are compared with
    the rows that passed before. Capacity is fixed: past ``most_load`` the filter stops with an error rather than fail within a walk.
    """

    def __init__(self, spark: SparkSession, folder: str, spec: FilterSpec, n: int, most_load: float = 0.99, exact: list[str] | None = None):
        self.spark, self.folder, self.most_load, self.exact = spark, folder.rstrip("/"), most_load, exact
        empty = spark.createDataFrame([], "key long")
        first = build_filter(empty, "key", spec, n, filter_id="online")
        self.spec = FilterSpec.from_json(first.select("spec").first()[0])
        save_filter(first, self._version(0), "overwrite")

    def _version(self, batch: int) -> str:
        return f"{self.folder}/filter/version={batch:08d}"

    def table(self, batch: int) -> DataFrame:
        return self.spark.read.schema(FILTER_SCHEMA).parquet(self._version(batch))

    def _step(self, rows: DataFrame, batch: int, key: str, order: str) -> None:
        before = self.table(batch)
        known = contains(rows.where(F.col(key).isNotNull()), key, before)
        names = rows.columns
        if self.exact:
            new, by = self._unlike_passed(known, batch).drop("hit"), self.exact
        else:
            new, by = with_signature(known.where("not hit").drop("hit"), F.col(key), self.spec), ["sub", "w0", "fp"]
        first = new.groupBy(*by).agg(F.min_by(F.struct(*names), F.struct(order, key)).alias("r")).select("r.*")
        out = f"{self.folder}/first/batch={batch:08d}"
        first.write.mode("overwrite").parquet(out)
        kept = self.spark.read.schema(first.schema).parquet(out)
        after = insert_into(before, kept, key)
        after.write.mode("overwrite").partitionBy("filter_id").parquet(self._version(batch + 1))
        state = self.table(batch + 1).agg(F.max(F.col("n_stored") / F.col("n_slots")), F.sum((F.col("status") != "ok").cast("int"))).first()
        if state[1]:
            raise RuntimeError("a subfilter is full: start a new generation and probe both")

    def _unlike_passed(self, known: DataFrame, batch: int) -> DataFrame:
        """The rows whose exact columns no earlier batch let through; only hits are compared."""
        if not batch:
            return known
        passed = self.spark.read.parquet(*[f"{self.folder}/first/batch={b:08d}" for b in range(batch)])
        passed = passed.select(*[F.col(c).alias(f"passed_{i}") for i, c in enumerate(self.exact)])
        same = reduce(lambda a, b: a & b, [F.col(c).eqNullSafe(F.col(f"passed_{i}")) for i, c in enumerate(self.exact)])
        return known.join(passed, F.col("hit") & same, "left_anti")

    def run(self, stream: DataFrame, key: str, order: str, checkpoint: str) -> None:
        """Process what the stream has now; ``order`` says which of equal entries in a batch comes first."""
        query = (
            stream.writeStream.foreachBatch(lambda rows, batch: self._step(rows, batch, key, order))
            .option("checkpointLocation", checkpoint)
            .trigger(availableNow=True)
            .start()
        )
        query.awaitTermination()

    def first_seen(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.folder}/first").drop("batch")


def exact_first_seen(stream: DataFrame, keys: list[str], time: str, delay: str) -> DataFrame:
    """The exact counterpart with bounded state: repeats within the watermark are dropped."""
    return stream.withWatermark(time, delay).dropDuplicatesWithinWatermark(keys)


def unseen_counts(stream: DataFrame, key: Column | str, table: DataFrame, time: str, width: str, delay: str, slide: str | None = None, session: bool = False) -> DataFrame:
    """Rows and surely new rows by event-time window: tumbling, sliding (``slide``) or session (``width`` is its gap)."""
    marked = probe_stream(stream, key, table).withWatermark(time, delay)
    window = F.session_window(time, width) if session else F.window(time, width, slide) if slide else F.window(time, width)
    got = marked.groupBy(window.alias("w")).agg(F.count(F.lit(1)).alias("rows"), F.sum((~F.col("hit")).cast("long")).alias("unseen"))
    return got.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "rows", "unseen")
