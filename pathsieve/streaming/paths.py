"""Chronological paths over edge streams. Such a path only grows at its end, so that new edges extend stored prefixes."""

from __future__ import annotations

import itertools
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import IntegerType, StructField, StructType

from pathsieve.functions import constraints as C
from pathsieve.operators import levels
from pathsieve.plans.graph import PropertyGraph
from pathsieve.plans.spec import GuardedPathQuery

EDGE = "id long, src long, dst long, label string, ts timestamp"
#: Extensions of stateful_paths that are in memory at once, for each edge of a path.
PART = 1 << 18
#: Stands for a missing vertex, which no edge leaves.
NOWHERE = np.iinfo(np.int64).min


def _micros(ts: pd.Series) -> np.ndarray:
    """Times as microseconds since 1970."""
    return ts.dt.tz_localize(None).to_numpy("datetime64[us]").astype(np.int64)


def run_to_end(stream: DataFrame, folder: str, mode: str = "append") -> DataFrame:
    """Processes all that is there into Parquet files under `folder`, and reads them. Each batch has a folder of its own, which it replaces when it runs again; in the complete mode the last one counts."""

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/rows/batch={batch_id}")

    query = stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    spark = stream.sparkSession
    schema = StructType([*stream.schema.fields, StructField("batch", IntegerType())])
    try:
        out = spark.read.schema(schema).parquet(f"{folder}/rows")
    except AnalysisException:  # no batch at all
        return spark.createDataFrame([], stream.schema)
    if mode == "complete":
        out = out.where(F.col("batch") == out.agg(F.max("batch")).first()[0])
    return out.select(*stream.columns)


def chain(first: DataFrame, second: DataFrame, gap: str) -> DataFrame:
    """Two edges in a row, the second later by at most `gap`: a stream-stream join that forgets by the watermarks. Edges: (id, src, dst, ts)."""
    a = first.select(F.col("id").alias("id1"), "src", F.col("dst").alias("mid"), F.col("ts").alias("ts1"))
    b = second.select(F.col("id").alias("id2"), F.col("src").alias("mid2"), "dst", F.col("ts").alias("ts2"))
    return a.join(b, F.expr(f"mid = mid2 AND ts2 > ts1 AND ts2 <= ts1 + INTERVAL {gap}"))


def tumbling(edges: DataFrame, width: str, *by: str) -> DataFrame:
    return edges.groupBy(F.window("ts", width), *by).agg(F.count(F.lit(1)).alias("n"))


def sliding(edges: DataFrame, width: str, slide: str, *by: str) -> DataFrame:
    return edges.groupBy(F.window("ts", width, slide), *by).agg(F.count(F.lit(1)).alias("n"))


def sessions(edges: DataFrame, gap: str, *by: str) -> DataFrame:
    return edges.groupBy(F.session_window("ts", gap), *by).agg(F.count(F.lit(1)).alias("n"))


def dedupe(edges: DataFrame) -> DataFrame:
    """Replayed edges within the watermark count once."""
    return edges.dropDuplicatesWithinWatermark(["id"])


def incremental_paths(spark: SparkSession, edges: DataFrame, store: str, starts: DataFrame, max_len: int, checkpoint: str) -> DataFrame:
    """Chronological paths from the starts, kept up batch by batch: (start, v, len, last_t, batch).

    Every micro-batch extends the stored prefixes by its edges, and its own extensions
    again, up to max_len. A batch must hold later edges than those before it, as an
    ordered file stream does; edges that come late are to be replayed in a new store.
    Each batch writes its own folder, so that a batch that is run again replaces itself.
    """
    schema = "start long, v long, len int, last_t timestamp"

    def extend(batch: DataFrame, batch_id: int) -> None:
        fresh = batch.select("src", "dst", "ts").persist()
        seeds = starts.select(F.col("v").alias("start"), "v", F.lit(0).alias("len"), F.lit(None).cast("timestamp").alias("last_t"))
        try:
            stored = spark.read.schema(schema + ", batch int").parquet(store).where(F.col("batch") < batch_id).drop("batch")
        except Exception as missing:  # no batch has written yet
            if "PATH_NOT_FOUND" not in str(missing):
                raise
            stored = spark.createDataFrame([], schema)
        now, found, held = stored.unionByName(seeds), None, [fresh]
        for _ in range(max_len):
            now = now.where(F.col("len") < max_len).join(fresh, F.col("v") == F.col("src")).where("last_t IS NULL OR ts > last_t").select("start", F.col("dst").alias("v"), (F.col("len") + 1).alias("len"), F.col("ts").alias("last_t")).persist()
            held.append(now)
            found = now if found is None else found.unionByName(now)
        found.write.mode("overwrite").parquet(f"{store}/batch={batch_id}")
        for x in held:
            x.unpersist()

    query = edges.writeStream.foreachBatch(extend).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(schema + ", batch int").parquet(store)


def stateful_spread(edges: DataFrame, window_us: int) -> DataFrame:
    """(src, id, n): for each edge, how many edges left its source within the window before it: keyed state that expires by event time. Edges: (id, src, ts)."""

    def step(key: tuple[int], frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        rows = pd.concat(list(frames)).sort_values(["ts", "id"])  # a key's edges may come in several frames, which are not in time order
        fresh, before = _micros(rows["ts"]), np.array(state.get[0] if state.exists else [], np.int64)
        times = np.concatenate([before, fresh])
        order = np.argsort(times, kind="stable")
        times, place = times[order], np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        n = place[len(before) :] - np.searchsorted(times, fresh - window_us)
        held = times[times >= times[-1] - window_us].tolist()
        state.update((held,))
        state.setTimeoutTimestamp(max((held[-1] + window_us) // 1000, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"src": key[0], "id": rows["id"].to_numpy(), "n": n})

    return edges.groupBy("src").applyInPandasWithState(step, "src long, id long, n long", "times array<long>", "append", GroupStateTimeout.EventTimeTimeout)


def stateful_paths(edges: DataFrame, by: str, window_us: int, max_len: int) -> DataFrame:
    """(by, first, last, len): chronological paths of up to max_len edges that agree in `by` and whose last edge is at most the window after the first. Edges: (id, src, dst, ts, by).

    The state of a key holds the prefixes that may still grow, with the time of their
    first edge; one expires when the window has passed since then, and the key's timer
    clears what is left when no edge comes. Within a batch a key's edges are met by their
    source and time, so that an edge costs the paths that it extends, and rows are handed
    on in parts; edges below the watermark are dropped (extend_late() makes up for them).
    """
    names = ["v", "head", "begin", "at", "n"]

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        rows = pd.concat(list(frames)).sort_values(["ts", "id"])
        edge, at = {n: rows[n].fillna(NOWHERE).to_numpy(np.int64) for n in ("id", "src", "dst")}, _micros(rows["ts"])
        moments, sources = np.unique(at), np.unique(edge["src"])
        where = np.searchsorted(sources, edge["src"]) * (len(moments) + 1) + np.searchsorted(moments, at)
        order = np.argsort(where, kind="stable")
        where, last = where[order], int(at[-1])
        kept: list[np.ndarray] = []

        def grown(prefixes: np.ndarray) -> Iterator[np.ndarray]:
            """The extensions of prefixes (a row for each of `names`) by the edges here, and theirs, in parts of bounded size."""
            kept.append(prefixes[:, (prefixes[2] >= last - window_us) & (prefixes[4] < max_len)])
            prefixes = prefixes[:, prefixes[4] < max_len]
            source = np.minimum(np.searchsorted(sources, prefixes[0]), len(sources) - 1)
            known = (sources[source] == prefixes[0]) & (prefixes[0] != NOWHERE)
            prefixes, source = prefixes[:, known], source[known] * (len(moments) + 1)
            low = np.searchsorted(where, source + np.searchsorted(moments, prefixes[3], "right"))
            high = np.searchsorted(where, source + np.searchsorted(moments, prefixes[2] + window_us, "right"))
            ends = np.cumsum(np.maximum(high - low, 0))
            for first in range(0, int(ends[-1]) if len(ends) else 0, PART):
                n = np.arange(first, min(first + PART, int(ends[-1])))
                which = np.searchsorted(ends, n, "right")
                e = order[high[which] - ends[which] + n]
                some = np.stack([edge["dst"][e], prefixes[1, which], prefixes[2, which], at[e], prefixes[4, which] + 1, edge["id"][e]])
                yield some
                yield from grown(some)

        stored = np.array(state.get, np.int64) if state.exists else np.empty((len(names), 0), np.int64)
        single = np.stack([edge["dst"], edge["id"], at, at, np.ones(len(at), np.int64), edge["id"]])
        for part in itertools.chain([single], grown(stored), grown(single)):
            yield pd.DataFrame({by: key[0], "first": part[1], "last": part[5], "len": part[4]})
        held = np.concatenate([k[: len(names)] for k in kept], axis=1)
        state.update(tuple(x.tolist() for x in held))
        state.setTimeoutTimestamp(max((int(held[2].max(initial=0)) + window_us) // 1000, state.getCurrentWatermarkMs() + 1))

    kind = edges.schema[by].dataType.simpleString()
    return edges.groupBy(by).applyInPandasWithState(step, f"{by} {kind}, first long, last long, len long", ", ".join(f"{n} array<long>" for n in names), "append", GroupStateTimeout.EventTimeTimeout)


def extend_late(stored: DataFrame, late: DataFrame, starts: DataFrame, max_len: int) -> DataFrame:
    """(start, v, len, last_t): the chronological paths that late edges add to those of the stored edges: all that hold a late edge, and no other. Edges: (id, src, dst, ts)."""
    micros = F.unix_micros(F.col("ts"))
    both = stored.select("id", "src", "dst", micros.alias("t"), F.lit(0).alias("late")).unionByName(late.select("id", "src", "dst", micros.alias("t"), F.lit(1).alias("late")))
    graph = PropertyGraph(both.withColumn("label", F.lit("")), alphabet=("",))
    rule = C.Monotone("t") & C.AnyOf("e_late = 1", "p_late[i] = 1", ["late"])
    rule = replace(rule, emit={"last_t": "timestamp_micros(s_last_t)"})
    return levels.paths(GuardedPathQuery(graph, rule, sources=starts, max_len=max_len), with_ids=False)
