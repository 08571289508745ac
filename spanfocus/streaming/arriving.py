"""Arriving documents: streaming scores, selection by micro-batch, windows with watermarks, joins, dedupe."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spanfocus.geometry import Geometry
from spanfocus.operators import lexical, samples, select
from spanfocus.operators.ranks import running_in_groups
from spanfocus.plans.entry_table import EntryTable
from spanfocus.session import cut, ensure_checkpoint_dir
from spanfocus.sources.tables import DOCUMENTS, read_table, stream_documents

TABLE = EntryTable()
EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
WATERMARK = "2 hours"


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there, into Parquet beside the checkpoints, and read that.

    In complete mode each batch replaces the one before.
    """
    spark = stream.sparkSession
    folder = shared_folder(spark)
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/log").trigger(availableNow=True)
    if mode == "complete":
        writer = writer.foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(f"{folder}/rows"))
    else:
        writer = writer.format("parquet").option("path", f"{folder}/rows")
    writer.start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/rows")


def stream_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Arriving events with ``ts`` as a timestamp, which watermarks need."""
    rows = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def score_stream(stream: DataFrame, table: lexical.WeightTable, geometry: Geometry, domain: str = "source") -> DataFrame:
    """Scores of arriving documents. The weight table is a frozen snapshot, so a score never moves later."""
    kept = samples.samples(stream, geometry, domain)
    return lexical.score_documents(kept, table, geometry)


class RunningSelection:
    """A selection kept up to date by micro-batches: each batch is merged once, replays change nothing.

    Candidates are written by batch under ``folder``, with a histogram of their tokens by score, ``BINS`` bins
    a domain and batch. Quotas move with the domains' totals, so a candidate below today's cut may be taken
    later: none is thrown away. But the histograms alone tell in which bin a domain's cut lies, so
    :meth:`current` orders only the candidates at or above that bin.
    """

    #: Bins of the histograms: sixteenths of powers of two of the score, from the lowest value up.
    BINS = 1024

    def __init__(self, spark: SparkSession, folder: str, share: float, score: str) -> None:
        self.spark, self.folder, self.share, self.score = spark, folder, share, score

    @classmethod
    def bin_of(cls, score: Column) -> Column:
        """A number that never falls as the score rises, for scores of any size and either sign."""
        size = F.least(F.lit(cls.BINS / 2 - 1), F.floor(16 * F.log2(1 + F.abs(score) * 2**20) / 2)).cast("int")
        return F.when(score < 0, -size).otherwise(size)

    def merge(self, batch: DataFrame, batch_id: int) -> None:
        rows = batch.select("doc_id", "domain", "n_tokens", F.round(self.score, select.PLACES).alias("score"))
        rows = rows.withColumn("bin", self.bin_of(F.col("score")))
        rows.write.mode("overwrite").parquet(f"{self.folder}/candidates/batch={batch_id}")
        kept = self.spark.read.schema(rows.schema).parquet(f"{self.folder}/candidates/batch={batch_id}")
        kept.groupBy("domain", "bin").agg(F.sum("n_tokens").alias("tokens")).coalesce(1).write.mode("overwrite").parquet(f"{self.folder}/histograms/batch={batch_id}")

    def cuts(self) -> DataFrame:
        """(domain, quota_tokens, bin): the lowest bin that the domain's quota reaches, from the histograms alone."""
        bins = self.spark.read.parquet(f"{self.folder}/histograms").groupBy("domain", "bin").agg(F.sum("tokens").alias("tokens"))
        bins = cut(bins)
        total = bins.agg(F.sum("tokens")).first()[0] or 0
        wanted = select.quotas(bins.groupBy("domain").agg(F.sum("tokens").alias("tokens")), int(total * self.share))
        above = F.sum("tokens").over(Window.partitionBy("domain").orderBy(F.desc("bin")).rowsBetween(Window.unboundedPreceding, -1))
        reached = bins.withColumn("above", F.coalesce(above, F.lit(0))).join(wanted, "domain").where(F.col("above") <= F.col("quota_tokens"))
        return reached.groupBy("domain", "quota_tokens").agg(F.min("bin").alias("low"))

    def current(self) -> DataFrame:
        rows = self.spark.read.parquet(f"{self.folder}/candidates").drop("batch")
        near = rows.join(self.cuts(), "domain").where(F.col("bin") >= F.col("low")).select("doc_id", "domain", "n_tokens", "score", "quota_tokens")
        placed = running_in_groups(near, "domain", F.desc("score"), F.col("doc_id"))
        return placed.where(F.col("cum_tokens") <= F.col("quota_tokens")).select(*select.COLUMNS)


def shared_folder(spark: SparkSession) -> str:
    """A new folder beside the checkpoints, which all executors share."""
    ensure_checkpoint_dir(spark)
    return f"{spark.sparkContext._jsc.sc().getCheckpointDir().get()}/stream-{uuid.uuid4().hex}"


def _files(sf_dir: str, name: str) -> str:
    # A pattern, since a stream's path may be a single file only then.
    return f"{sf_dir}/{name}.parque[t]"


def register(method_scores: str, method_selection: str) -> None:
    """Register the streaming queries; the two arguments are the oracles of their batch twins."""
    g = Geometry.named("desk")

    def op_stream_score(spark: SparkSession, sf_dir: str) -> DataFrame:
        table = lexical.weight_table(read_table(spark, sf_dir, "documents"))
        made = drained(score_stream(stream_documents(spark, _files(sf_dir, "documents"), DOCUMENTS), table, g))
        return made.select("doc_id", (F.round("full_4_4", 6) + F.lit(0.0)).alias("dependency"))

    def op_stream_select(spark: SparkSession, sf_dir: str) -> DataFrame:
        table = lexical.weight_table(read_table(spark, sf_dir, "documents"))
        running = RunningSelection(spark, shared_folder(spark), 0.25, "full_4_4")
        stream = score_stream(stream_documents(spark, _files(sf_dir, "documents"), DOCUMENTS), table, g)
        stream.writeStream.foreachBatch(running.merge).trigger(availableNow=True).start().awaitTermination()
        return running.current().withColumn("score", F.round("score", 6) + F.lit(0.0))

    TABLE.add("op_stream_score", op_stream_score, method_scores)
    TABLE.add("op_stream_select", op_stream_select, method_selection)


#: Far later than any event: the watermark passes all windows of the events before it.
_CLOSING = "2999-01-01 00:00:00"
_ALL_FILES = 2**31 - 1


def windowed(rows: DataFrame, window: Column, keys: list[str], watermark: str = WATERMARK) -> DataFrame:
    """Counts and sums by window in append mode: a window comes out, once, when the watermark has passed its end,
    and its state is dropped. Events later than that are dropped too."""
    return rows.withWatermark("ts", watermark).groupBy(window.alias("w"), *keys).agg(F.count("*").alias("n"), F.sum("value").alias("value"))


def closed(spark: SparkSession, sf_dir: str, query: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Append-mode result of a windowed query over the table of events and a closing event.

    All files come as one batch, so no event is late, whatever the order of the files. The closing event
    moves the watermark past every window, and the trigger's last batch, without data, puts them out.
    """
    path = f"{shared_folder(spark)}/closing"
    row = spark.range(1).select(F.lit(None).cast("bigint").alias("event_id"), F.lit(_CLOSING).cast("timestamp_ntz").alias("ts"), F.lit(0.0).alias("value"))
    row.coalesce(1).write.parquet(path)
    rows = stream_events(spark, _files(sf_dir, "events"), _ALL_FILES).unionByName(stream_events(spark, path, _ALL_FILES))
    return drained(query(rows)).where(F.col("w.start") < F.to_timestamp(F.lit(_CLOSING)) - F.expr("INTERVAL 2 DAYS"))


def _windowed(window: Callable[[], Column], keys: list[str]) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = closed(spark, sf_dir, lambda rows: windowed(rows, window(), keys))
        return out.select(F.unix_seconds("w.start").alias("start_s"), F.unix_seconds("w.end").alias("end_s"), *keys, "n", F.round("value", 4).alias("value"))

    return query


TABLE.add(
    "op_stream_tumbling",
    _windowed(lambda: F.window("ts", "1 day"), ["event_type"]),
    """SELECT epoch_us(ts) // 86400000000 * 86400 AS start_s, epoch_us(ts) // 86400000000 * 86400 + 86400 AS end_s, event_type, count(*) AS n,
    round(sum(value), 4) AS value FROM events GROUP BY ALL""",
)
TABLE.add(
    "op_stream_sliding",
    _windowed(lambda: F.window("ts", "12 hours", "6 hours"), ["event_type"]),
    """WITH s AS (SELECT *, unnest([epoch_us(ts) // 21600000000 * 21600, epoch_us(ts) // 21600000000 * 21600 - 21600]) AS start_s FROM events)
    SELECT start_s, start_s + 43200 AS end_s, event_type, count(*) AS n, round(sum(value), 4) AS value FROM s GROUP BY ALL""",
)


@TABLE.query("""WITH o AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    g AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM o)
    SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM g GROUP BY user_id, g""")
def op_stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions end after half an hour without an event. Append mode: a session comes out once the watermark has
    passed its end, which the closing event sees to."""
    made = closed(spark, sf_dir, lambda rows: windowed(rows, F.session_window("ts", "30 minutes"), ["user_id"]))
    return made.select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


@TABLE.query("""SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click'
    AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR""")
def op_stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream-stream interval join: purchases within the hour after a click of the same user."""
    one = stream_events(spark, _files(sf_dir, "events"))
    clicks = one.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("u"), F.col("ts").alias("at")).withWatermark("at", WATERMARK)
    buys = one.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", "ts").withWatermark("ts", WATERMARK)
    near = (F.col("u") == F.col("user_id")) & (F.col("ts") >= F.col("at")) & (F.col("ts") <= F.col("at") + F.expr("INTERVAL 1 HOUR"))
    return drained(clicks.join(buys, near)).select("click_id", "purchase_id")


@TABLE.query("SELECT event_type, r_name, count(*) AS n FROM events JOIN region ON user_id % 5 = r_regionkey GROUP BY ALL")
def op_stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream joined with a static table of five rows."""
    rows = stream_events(spark, _files(sf_dir, "events")).withColumn("r_regionkey", F.pmod("user_id", F.lit(5)).cast("int"))
    made = rows.join(read_table(spark, sf_dir, "region"), "r_regionkey").groupBy("event_type", "r_name").agg(F.count("*").alias("n"))
    return drained(made, "complete")


@TABLE.query("SELECT md5(coalesce(text, '')) AS digest FROM documents GROUP BY 1")
def op_stream_dedupe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct texts of arriving documents, by digest."""
    rows = stream_documents(spark, _files(sf_dir, "documents"), DOCUMENTS)
    return drained(rows.select(F.md5(F.coalesce("text", F.lit(""))).alias("digest")).dropDuplicates(["digest"]))


@TABLE.query("SELECT event_id FROM events GROUP BY event_id")
def op_stream_dedupe_watermark(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events once each, remembered only as long as the watermark asks for."""
    rows = stream_events(spark, _files(sf_dir, "events")).withWatermark("ts", WATERMARK)
    return drained(rows.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))
