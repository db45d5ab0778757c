"""Serving: requests decoded to views, dialogue checks, newest view of a session, streams."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import array_engine
from ..plans.spec import CubeSpec, ViewSpec

#: What a request can choose from.
ANGLE_STEPS, ZOOMS = 24, 4
IDLE_MS = 60 * 86_400_000
# The dialogue of a session: state, message, next state.
TRANSITIONS = [
    ("init", "signup", "open"),
    *[("open", m, "open") for m in ("view", "click", "purchase")],
    ("open", "error", "closed"),
    ("closed", "signup", "open"),
]


def decode(events: DataFrame) -> DataFrame:
    """One event, one view request: frame, session, angle, zoom, map, arrival."""
    k = F.get_json_object("props", "$.k").cast("int")
    return events.select(
        F.col("event_id").alias("frame"),
        F.col("user_id").alias("session"),
        (F.lit(15) * (k % ANGLE_STEPS)).alias("angle"),
        (1 + (k % ZOOMS) / 2).alias("zoom"),
        F.col("event_type").alias("cmap"),
        "ts",
    )


def latest(requests: DataFrame) -> DataFrame:
    """Newest request of each session; the larger frame on ties."""
    return requests.groupBy("session").agg(F.max_by(F.struct("frame", "angle", "zoom", "cmap", "ts"), F.struct("ts", "frame")).alias("r")).select("session", "r.*")


def drawn(requests: DataFrame, blocks: DataFrame, cube: CubeSpec, side: int) -> DataFrame:
    """session, frame, angle, ts, u, v, val: the image of each request; one row without a pixel for a blank image.

    Requests choose among ``ANGLE_STEPS`` angles and ``ZOOMS`` zooms, so the views that are asked for are a bounded set: each is cast
    once, and sessions are joined to the images by their view."""
    asked = requests.select("angle", "zoom").distinct().collect()
    views = {(r["angle"], r["zoom"]): ViewSpec(float(r["angle"]), side, side, float(r["zoom"]), frame=i) for i, r in enumerate(asked)}
    names = requests.sparkSession.createDataFrame([(a, z, v.frame) for (a, z), v in views.items()], "angle int, zoom double, view long")
    images = array_engine.cast(blocks, cube, list(views.values())).groupBy(F.col("frame").alias("view"), "u", "v").agg(F.max("val").alias("val"))
    return requests.join(F.broadcast(names), ["angle", "zoom"]).join(images, "view", "left").select("session", "frame", "angle", "ts", "u", "v", "val")


def validate(events: DataFrame) -> DataFrame:
    """user_id, event_id, state after it and whether the message was allowed: sessions are sorted next to each other and walked once,
    batch by batch; what is held is one state, however long a session is."""
    table = {(s, m): n for s, m, n in TRANSITIONS}

    def walk(frames):
        state, user = "init", None
        for frame in frames:
            after, ok = [], []
            for u, m in zip(frame["user_id"], frame["event_type"], strict=True):
                if u != user:
                    user, state = u, "init"
                nxt = table.get((state, m))
                state = nxt or state
                after.append(state)
                ok.append(nxt is not None)
            yield pd.DataFrame({"user_id": frame["user_id"], "event_id": frame["event_id"], "state": after, "ok": ok})

    ordered = events.select("user_id", "ts", "event_id", "event_type").repartition("user_id").sortWithinPartitions("user_id", "ts", "event_id")
    return ordered.select("user_id", "event_id", "event_type").mapInPandas(walk, "user_id long, event_id long, state string, ok boolean")


def alternation(conversations: DataFrame) -> DataFrame:
    """conv_id, turn, ok: whether roles alternate user and assistant after an optional system turn."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    last = F.lag("role").over(w)
    ok = F.when(last.isNull(), F.col("role").isin("system", "user")).when(F.col("role") == "user", last.isin("system", "assistant")).when(F.col("role") == "assistant", last == "user").otherwise(False)
    return conversations.select("conv_id", "turn", ok.alias("ok"))


def timed(stream: DataFrame) -> DataFrame:
    """Event time as a zoned timestamp, which watermarks need."""
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def cube_stream(stream: DataFrame, top: int) -> DataFrame:
    """Incremental voxels of the event cube; the extent is known in advance."""
    minute = F.hour("ts") * 60 + F.minute("ts")
    v = stream.select(F.expr(f"user_id * 27 div {top}").alias("x"), F.floor(minute * 27 / 1440).alias("y"), F.floor((F.dayofmonth("ts") - 1) * 16 / 30).alias("z"), F.round(F.col("value") * 100).cast("long").alias("v"))
    return v.groupBy("x", "y", "z").agg(F.sum("v").alias("v"))


def mip_stream(stream: DataFrame, top: int) -> DataFrame:
    """Incremental projection of single deposits along z: a maximum never retracts."""
    minute = F.hour("ts") * 60 + F.minute("ts")
    v = stream.select(F.expr(f"user_id * 27 div {top}").alias("u"), F.floor(minute * 27 / 1440).alias("w"), F.round(F.col("value") * 100).cast("long").alias("v"))
    return v.groupBy("u", "w").agg(F.max("v").alias("val"))


def session_states(stream: DataFrame) -> DataFrame:
    """The automaton as a stateful stream: user_id, n, state, refused; a session without messages for sixty days of event time is dropped. The stream needs a watermark."""
    table = {(s, m): n for s, m, n in TRANSITIONS}

    def step(key, frames, state: GroupState):
        if state.hasTimedOut:
            state.remove()
            return
        name, n, refused = state.get if state.exists else ("init", 0, 0)
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        for m in rows["event_type"]:
            nxt = table.get((name, m))
            name, n, refused = nxt or name, n + 1, refused + (nxt is None)
        state.update((name, n, refused))
        state.setTimeoutTimestamp(int(rows["ts"].max().timestamp() * 1000) + IDLE_MS)
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "state": [name], "refused": [refused]})

    return stream.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, state string, refused long", "state string, n long, refused long", "append", GroupStateTimeout.EventTimeTimeout)


def start(stream: DataFrame, render: Callable[[DataFrame], DataFrame], sink: str, checkpoint: str):
    """Each micro-batch renders the newest view of every session into a folder of its own; a replayed batch overwrites it."""

    def batch(df: DataFrame, number: int) -> None:
        render(latest(decode(df))).write.mode("overwrite").parquet(f"{sink}/batch={number}")

    return stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def pipeline(jobs: list[Callable[[], object]], depth: int = 3) -> list[object]:
    """Independent frames in flight together, in the FAIR pool if the session has one."""
    with ThreadPoolExecutor(depth) as pool:
        return list(pool.map(lambda j: j(), jobs))
