"""The methods on streams of points: replayable two-pass runs, one-pass shards and keyed state, windows and watermarks."""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import scans
from ..baselines import OnePassState, one_pass_shards
from ..hitting import complete, hitting_set
from ..methods import coordinate_at, summarise
from ..metrics import Metric
from ..model import Points
from ..storage import new_path, scratch


def drain(stream: DataFrame, each: Callable[[DataFrame, int], None]) -> None:
    """Run a stream over what is available now, batch by batch."""
    query = stream.writeStream.foreachBatch(each).trigger(availableNow=True).option("checkpointLocation", new_path(stream.sparkSession, "progress")).start()
    query.awaitTermination()
    if query.exception():
        raise query.exception()


class BatchState:
    """A few rows after each batch, as one small table a batch in the shared folder; a batch that runs again overwrites its own."""

    def __init__(self, spark: SparkSession, schema: str):
        self.spark, self.schema, self.path = spark, schema, new_path(spark, "state")

    def before(self, number: int) -> list[tuple]:
        place = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        files = place.getFileSystem(self.spark._jsc.hadoopConfiguration())
        known = [int(x.getPath().getName()) for x in files.listStatus(place)] if files.exists(place) else []
        last = max((n for n in known if n < number), default=None)
        return [] if last is None else [tuple(r) for r in self.spark.read.schema(self.schema).parquet(f"{self.path}/{last}").collect()]

    def put(self, number: int, rows: list[tuple]) -> None:
        self.spark.createDataFrame(rows, self.schema).coalesce(1).write.mode("overwrite").parquet(f"{self.path}/{number}")

    def latest(self) -> list[tuple]:
        return self.before(1 << 62)


def two_pass_stream(source: Callable[[], DataFrame], metric: Metric, caps: tuple[int, ...], tau: float) -> tuple[Points | None, int, int]:
    """Two passes over a replayable stream at one guess: (centres, sets met, sets).

    State after each batch is the pivots, then for each pivot and group the
    representative of smallest ord.
    """
    k = sum(caps)
    spark = source().sparkSession
    pivot_state = BatchState(spark, f"ord bigint, grp int, coords {metric.coords}")

    def first(batch: DataFrame, number: int) -> None:
        held = sorted(pivot_state.before(number))
        more = scans.separated_pivots(_beyond(batch, metric, held, 2 * tau), metric, [2 * tau], k)[0][0].rows(metric)
        pivot_state.put(number, held + more)

    drain(source(), first)
    pivots = Points.of(sorted(pivot_state.latest()), metric)
    if len(pivots) > k or not len(pivots):
        return None, 0, len(pivots)
    rep_state = BatchState(spark, f"pivot int, ord bigint, grp int, coords {metric.coords}")

    def second(batch: DataFrame, number: int) -> None:
        held = {(p, g): (p, o, g, c) for p, o, g, c in rep_state.before(number)}
        (sets,) = scans.group_reps(batch, metric, [pivots], [tau])
        for p, s in enumerate(sets):
            for o, g, c in s.rows(metric)[1:]:
                held[p, g] = min(held.get((p, g), (p, o, g, c)), (p, o, g, c), key=lambda r: r[1])
        rep_state.put(number, list(held.values()))

    drain(source(), second)
    found = sorted(rep_state.latest(), key=lambda r: (r[0], r[2]))
    sets = [Points.of([row, *(r[1:] for r in found if r[0] == p and r[2] != row[1])], metric) for p, row in enumerate(pivots.rows(metric))]
    chosen, hits = hitting_set(sets, caps)
    return chosen, hits, len(sets)


def _beyond(points: DataFrame, metric: Metric, held: list[tuple], radius: float) -> DataFrame:
    if not held:
        return points
    few = F.array(*[scans._literal(c, metric) for _, _, c in held])
    return points.where(F.array_min(F.transform(few, lambda c: metric.column(F.col("coords"), c))) > radius)


def coordinate_guesses(kept: dict[int, list[tuple[str, int, tuple]]], metric: Metric, caps: tuple[int, ...], guesses: list[float]) -> tuple[int, Points, int] | None:
    """The smallest guess that the coordinator can finish from what shards kept, with its centres and sets; a guess that a shard broke has failed."""
    for g, tau in enumerate(guesses):
        rows = kept.get(g, [])
        if not rows or any(role == "broken" for role, _, _ in rows):
            continue
        x, l = (Points.of([r for role, _, r in rows if role == kind], metric).sorted() for kind in ("pivot", "rep"))
        chosen, hits, sets = coordinate_at(x, l, metric, caps, tau)
        if chosen is not None and hits == sets:
            return g, complete(chosen, caps, l), sets
    return None


def one_pass_stream(stream: DataFrame, metric: Metric, caps: tuple[int, ...], guesses: list[float]) -> tuple[float, Points, int] | None:
    """One pass over a stream for several guesses: the smallest that succeeds, its centres and sets, or None.

    Every partition of every batch is a shard of the one-pass method; what it
    keeps for all guesses is written under the batch's number, so a batch that
    runs again overwrites its own, and the driver holds nothing in between.
    """
    path = new_path(stream.sparkSession, "shards")

    def each(batch: DataFrame, number: int) -> None:
        one_pass_shards(batch, metric, caps, guesses).write.mode("overwrite").parquet(f"{path}/batch={number}")

    drain(stream, each)
    kept: dict[int, list[tuple[str, int, tuple]]] = {}
    for r in stream.sparkSession.read.parquet(path).collect():
        kept.setdefault(r.g, []).append((r.role, r.pivot, (r.ord, r.grp, r.coords)))
    found = coordinate_guesses(kept, metric, caps, guesses)
    return None if found is None else (guesses[found[0]], found[1], found[2])


def one_pass_keyed(stream: DataFrame, metric: Metric, caps: tuple[int, ...], guesses: list[float], name: str) -> DataFrame:
    """One-pass state per key of a stream of (key, ord, grp, coords): (key, arrivals, kept), the state after the last batch that had rows of it.

    The state is what :class:`OnePassState` holds for every guess, at most k
    pivots and their quotas, in the query's state store; ``kept`` is its JSON,
    which :func:`finish_key` turns into centres.
    """
    import pandas as pd

    def load(text: str) -> list[OnePassState]:
        states = []
        for t, (broken, pivots, reps) in zip(guesses, json.loads(text)):
            state = OnePassState(metric, caps, t)
            state.broken = broken
            state.pivots = Points.of(pivots, metric) if pivots else None
            state.reps = [{int(g): [tuple(r) for r in have] for g, have in held.items()} for held in reps]
            states.append(state)
        return states

    def step(key: tuple, frames: Iterator[pd.DataFrame], group) -> Iterator[pd.DataFrame]:
        arrivals, text = group.get if group.exists else (0, None)
        states = load(text) if text else [OnePassState(metric, caps, t) for t in guesses]
        rows = pd.concat(list(frames)).sort_values("ord", kind="stable")
        more = Points.of([(o, g, c.tolist() if isinstance(c, np.ndarray) else c) for o, g, c in zip(rows["ord"], rows["grp"], rows["coords"])], metric)
        for state in states:
            state.insert(more)
        text = json.dumps([(s.broken, [] if s.pivots is None else s.pivots.rows(metric), s.reps) for s in states])
        group.update((arrivals + len(rows), text))
        yield pd.DataFrame({"key": [key[0]], "arrivals": [arrivals + len(rows)], "kept": [text]})

    kept = stream.select("key", "ord", "grp", "coords").groupBy("key").applyInPandasWithState(step, "key string, arrivals bigint, kept string", "arrivals bigint, kept string", "update", "NoTimeout")
    query = kept.writeStream.format("memory").queryName(name).outputMode("update").trigger(availableNow=True).option("checkpointLocation", new_path(stream.sparkSession, "progress")).start()
    query.awaitTermination()
    return stream.sparkSession.table(name).groupBy("key").agg(F.max("arrivals").alias("arrivals"), F.max_by("kept", "arrivals").alias("kept"))


def finish_key(text: str, metric: Metric, caps: tuple[int, ...], guesses: list[float]) -> tuple[int, Points, int] | None:
    """(guess number, centres, sets) of one key's state."""
    kept = {}
    for g, (broken, pivots, reps) in enumerate(json.loads(text)):
        kept[g] = [("broken", 0, ())] if broken else [("pivot", p, tuple(r)) for p, r in enumerate(pivots)] + [("rep", p, tuple(r)) for p, held in enumerate(reps) for have in held.values() for r in have]
    return coordinate_guesses(kept, metric, caps, guesses)


def window_summaries(points: DataFrame, metric: Metric, caps: tuple[int, ...], length: str, parts: int = 1) -> DataFrame:
    """The block message of every tumbling window of (ord, grp, coords, ts): (window_start, part, ord, grp, coords, r), pivots and representatives once each.

    A window whose rows are too many for one task is cut into ``parts`` blocks
    by ord, each with its own message; a coordinator takes them together.
    """
    k = sum(caps)

    def one(table):
        import pyarrow as pa

        column = table["coords"].combine_chunks()
        ords, grps = table["ord"].to_numpy(), table["grp"].to_numpy()
        pivots, reps, r = summarise(ords, grps, metric.load(column), metric, k)
        at = sorted({*pivots, *(i for _, i in reps)}, key=lambda i: ords[i])
        return pa.table({"window_start": table["w"].take(pa.array(at)), "part": table["part"].take(pa.array(at)), "ord": ords[at], "grp": pa.array(grps[at], pa.int32()), "coords": column.take(pa.array(at)), "r": np.full(len(at), r)})

    rows = points.select(F.window("ts", length)["start"].alias("w"), F.pmod("ord", F.lit(parts)).cast("int").alias("part"), "ord", "grp", "coords")
    return rows.groupBy("w", "part").applyInArrow(one, f"window_start timestamp, part int, ord bigint, grp int, coords {metric.coords}, r double")


def _in_memory(frame: DataFrame, name: str, mode: str) -> DataFrame:
    query = frame.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", new_path(frame.sparkSession, "progress")).start()
    query.awaitTermination()
    return frame.sparkSession.table(name)


def _appended(frame: DataFrame, name: str) -> DataFrame:
    """All rows that the stream gives, as files in the shared folder: the driver holds none of them."""
    path = new_path(frame.sparkSession, name)
    with scratch():
        query = frame.writeStream.format("parquet").option("path", path).outputMode("append").trigger(availableNow=True).option("checkpointLocation", new_path(frame.sparkSession, "progress")).start()
        query.awaitTermination()
    return frame.sparkSession.read.schema(frame.schema).parquet(path)


def _last_result(frame: DataFrame, name: str) -> DataFrame:
    """The whole result after the last batch, as a table in the shared folder; two places take turns, so a batch never overwrites the one before."""
    path, last = new_path(frame.sparkSession, name), []

    def each(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{number % 2}")
        last[:] = [number]

    with scratch():
        query = frame.writeStream.foreachBatch(each).outputMode("complete").trigger(availableNow=True).option("checkpointLocation", new_path(frame.sparkSession, "progress")).start()
        query.awaitTermination()
    if not last:
        return frame.sparkSession.createDataFrame([], frame.schema)
    return frame.sparkSession.read.schema(frame.schema).parquet(f"{path}/{last[0] % 2}")


def watermark_counts(stream: DataFrame, delay: str, length: str, name: str) -> DataFrame:
    """Counts of a stream of (ts, grp) by window and group, late rows within the delay counted, read back from memory."""
    counted = stream.withWatermark("ts", delay).groupBy(F.window("ts", length), "grp").agg(F.count("*").alias("n"))
    return _in_memory(counted, name, "complete").select(F.col("window.start").alias("window_start"), "grp", "n")


def session_counts(stream: DataFrame, delay: str, gap: str, name: str) -> DataFrame:
    """Rows of a stream of (ts, key) in each session of a key; a session ends when nothing comes for the gap."""
    counted = stream.withWatermark("ts", delay).groupBy(F.session_window("ts", gap), "key").agg(F.count("*").alias("n"))
    return _last_result(counted, name).select("key", "n")


def distinct_within(stream: DataFrame, delay: str, keys: list[str], name: str) -> DataFrame:
    """The stream with repeats of its keys dropped, as long as they come within the delay."""
    return _appended(stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(keys), name)


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``events`` as a file stream; TIMESTAMP_NTZ becomes TIMESTAMP, which watermarks need."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))
