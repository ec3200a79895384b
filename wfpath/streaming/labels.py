"""Labels given while a run grows: each node is labelled when it appears and never again.

Whether a member of a chain is its last isn't known when it arrives, so the streamed
specification lets a second module say that later: a session is followed by MORE, which becomes
the next session or a halt.  Labels are then final at once.

Events behind the watermark are dropped before they reach a run.  A run whose last event is older
than ``keep`` behind the watermark is closed (pause, halt and end are told) and forgotten; what the
user does later is another run, so runs that may be closed are named by their first event too.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from wfpath.functions.labels import Decoder, pack
from wfpath.operators import allpairs
from wfpath.operators.pairwise import decided, masked
from wfpath.plans.safety import SafePlan
from wfpath.plans.spec import Spec
from wfpath.sources.runs import GAP

STREAMED = Spec.chain(
    "RUN",
    [
        ("RUN", "begin SESS end"), ("SESS", "VISIT MORE"), ("MORE", "SESS"), ("MORE", "halt"), ("VISIT", "arrive STEPS"), ("STEPS", "STEP REST"), ("REST", "STEPS"), ("REST", "pause"),
        ("STEP", "click ack"), ("STEP", "view ack"), ("STEP", "signup verify ack"), ("STEP", "purchase {charge ship} ack"), ("STEP", "error retry ack"),
    ],
)
_KINDS = {p.body[0]: p for p in STREAMED.productions if p.lhs == "STEP"}
OUT = "run_id string, node_id string, module string, label array<struct<kind:tinyint,a:int,b:int,idx:bigint>>"
STATE = "first long, session long, step long, last long"


def _entry(kind: int, a: int, b: int, idx: int = 0) -> dict:
    return {"kind": kind, "a": a, "b": b, "idx": idx}


def _closing(run: str, session: int, step: int) -> list[tuple]:
    """What ends a run: the last session's steps, the sessions, and the run."""
    visit = [_entry(0, 1, 2), _entry(1, 1, 1, 2 * session - 1), _entry(0, 2, 1)]
    pause = [*visit, _entry(0, 5, 2), _entry(1, 2, 1, 2 * step - 1), _entry(0, 6, 2), _entry(0, 8, 1)]
    halt = [_entry(0, 1, 2), _entry(1, 1, 1, 2 * session - 1), _entry(0, 2, 2), _entry(0, 4, 1)]
    return [(run, f"{run}.s{session}.pause", "pause", pause), (run, f"{run}.halt", "halt", halt), (run, f"{run}.end", "end", [_entry(0, 1, 3)])]


def growing(keep_ms: int | None):
    """The state function: new nodes of one run; the state is its first event's time and where it stands: session, step, time of the last event."""

    def grow(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        first, session, step, last = state.get if state.exists else (0, 0, 0, None)
        name = lambda: f"u{key[0]}" if keep_ms is None else f"u{key[0]}@{first}"
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame(_closing(name(), session, step), columns=["run_id", "node_id", "module", "label"])
            return
        rows = pd.concat(list(batches)).sort_values(["us", "event_id"])
        out = []
        for r in rows.itertuples():
            if r.event_type not in _KINDS:
                continue
            if last is None:
                first = int(r.us)
                out.append((name(), f"{name()}.begin", "begin", [_entry(0, 1, 1)]))
            run = name()
            if last is None or r.us - last > GAP:
                session, step = session + 1, 0
                visit = [_entry(0, 1, 2), _entry(1, 1, 1, 2 * session - 1), _entry(0, 2, 1)]
                out.append((run, f"{run}.s{session}.arrive", "arrive", [*visit, _entry(0, 5, 1)]))
            step, last = step + 1, int(r.us) if last is None else max(last, int(r.us))
            visit = [_entry(0, 1, 2), _entry(1, 1, 1, 2 * session - 1), _entry(0, 2, 1)]
            p = _KINDS[r.event_type]
            for i, m in enumerate(p.body, 1):
                out.append((run, f"{run}.s{session}.e{step}.{m}", m, [*visit, _entry(0, 5, 2), _entry(1, 2, 1, 2 * step - 1), _entry(0, 6, 1), _entry(0, p.number, i)]))
        if last is not None:
            state.update((first, session, step, last))
            if keep_ms is not None:
                state.setTimeoutTimestamp(max(last // 1000, state.getCurrentWatermarkMs()) + keep_ms)
        yield pd.DataFrame(out, columns=["run_id", "node_id", "module", "label"])

    return grow


def labelled(events: DataFrame, watermark: str = "1 day", keep_hours: float | None = None) -> DataFrame:
    """A stream of events (event_id, ts, user_id, event_type) as a stream of labelled nodes.

    Spark drops rows behind the watermark only with an event-time timeout, so that is what is set
    even if no run is ever closed (``keep_hours`` None).
    """
    e = events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type").withWatermark("ts", watermark)
    e = e.withColumn("us", F.unix_micros("ts"))
    keep = None if keep_hours is None else int(keep_hours * 3_600_000)
    return e.groupBy("user_id").applyInPandasWithState(growing(keep), OUT, STATE, "append", GroupStateTimeout.EventTimeTimeout)


def stream_of(spark: SparkSession, sf_dir: str, table: str = "events", files: int = 1) -> DataFrame:
    """A stored table as a stream of its files."""
    schema = spark.read.parquet(f"{sf_dir}/{table}.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", f"{table}.parquet").option("maxFilesPerTrigger", files).parquet(sf_dir)


def stored(stream: DataFrame, folder: str) -> DataFrame:
    """All that a stream has to give now, written as Parquet and read back."""
    spark, name = stream.sparkSession, uuid.uuid4().hex
    path = f"{folder}/stream-{name}"
    stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", f"{folder}/progress-{name}").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def replaced(stream: DataFrame, folder: str) -> DataFrame:
    """An aggregate over a whole stream: each micro-batch's complete result replaces the one before."""
    spark, name = stream.sparkSession, uuid.uuid4().hex
    path = f"{folder}/stream-{name}"
    write = lambda batch, number: batch.write.mode("overwrite").parquet(path)
    stream.writeStream.outputMode("complete").foreachBatch(write).option("checkpointLocation", f"{folder}/progress-{name}").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def probed(probes: DataFrame, nodes: DataFrame, plan: SafePlan) -> DataFrame:
    """A stream of probes (run_id, src, dst and more) against labels that are stored: the probes with ``holds``.

    Labels say all that a decision needs, so the stream keeps no state; an unknown node gives false.
    """
    decoder = Decoder(plan)
    u = masked(nodes, decoder, entries=False).select("run_id", F.col("node_id").alias("src"), F.col("label").alias("ulabel"), "exits")
    v = masked(nodes, decoder, exits=False).select("run_id", F.col("node_id").alias("dst"), F.col("label").alias("vlabel"), "entries")
    x = probes.join(u, ["run_id", "src"], "left").join(v, ["run_id", "dst"], "left")
    known = F.col("ulabel").isNotNull() & F.col("vlabel").isNotNull()
    return x.select(*probes.columns, F.when(known, decided(x, decoder)).otherwise(False).alias("holds"))


def followed(left: DataFrame, right: DataFrame, keys: list[str], at: str, other: str, within: str, watermark: str = "1 day") -> DataFrame:
    """Two streams joined where ``other`` lies in [at, at + within]; watermarks bound what is kept of both."""
    a, b = left.withWatermark(at, watermark), right.withWatermark(other, watermark)
    on = None
    for k in keys:
        same = a[k] == b[k]
        on = same if on is None else on & same
    x = a.join(b, on & (b[other] >= a[at]) & (b[other] <= a[at] + F.expr(f"INTERVAL {within}")))
    return x.select(*[a[c] for c in a.columns], *[b[c] for c in b.columns if c not in keys])


def hourly(events: DataFrame, every: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Events by tumbling or sliding window and type; works on streams and tables."""
    w = F.window(F.col("ts").cast("timestamp"), every, slide) if slide else F.window(F.col("ts").cast("timestamp"), every)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "12 hours") -> DataFrame:
    """Sessions by Spark's session window: user_id, start, end, n."""
    w = F.session_window(F.col("ts").cast("timestamp"), gap)
    return events.groupBy("user_id", w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def matched_with(plan: SafePlan, known: DataFrame, batch: DataFrame) -> DataFrame:
    """New pairs that a micro-batch of labelled nodes brings: known or new sources, new targets."""
    nodes = known.select("run_id", "node_id", "label").union(batch.select("run_id", "node_id", "label")).dropDuplicates(["run_id", "node_id"])
    return allpairs.state_set(nodes, plan, None, batch)


def with_keys(nodes: DataFrame) -> DataFrame:
    return nodes.select("run_id", "node_id", "module", F.lower(F.hex(pack(F.col("label")))).alias("label_key"))
