"""Continuous monitoring: the batch detector's semantics, record by record, with bounded state per device.

State per device is the last values of each metric, the last exponential averages and the last y verdicts; it
does not grow with time. Records older than the watermark are dropped and not used to correct the past.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.naming import Feature
from ..operators.grid import feature_matrix


def monitor(stream: DataFrame, thresholds: Sequence[dict], x: int, y: int, points_per_day: int, idle_minutes: int = 0, delay: str = "1 day") -> DataFrame:
    """(device, rec_id, ts, abnormal, hits, marked, dispatch) of a stream of telemetry, in time order per batch and device.

    thresholds: rows with feature, low, high (few). dispatch is true on the record that opens a fault. With idle_minutes, a
    device silent for so long (in processing time) loses its state.
    """
    from ..functions.naming import parse_feature

    tests = [(parse_feature(t["feature"]), t["low"], t["high"]) for t in thresholds]
    metrics = list(dict.fromkeys(f.metric for f, _, _ in tests))
    framed = [f for f, _, _ in tests if f.model != "ewma"]
    decays = [f for f, _, _ in tests if f.model == "ewma"]
    most = max([1, *[f.param * points_per_day for f in framed]])

    def averages_of(rows: pd.DataFrame, state: list) -> dict[Feature, np.ndarray]:
        """The exponential averages record by record, from the last ones on; the state moves along."""
        out = {f: np.full(len(rows), np.nan) for f in decays}
        for i, f in enumerate(decays):
            now, lam = state[i], f.param / 10
            for t, v in enumerate(rows[f.metric].to_numpy(float, na_value=np.nan).tolist()):
                if v == v:
                    now = v if now is None else lam * v + (1 - lam) * now
                out[f][t] = np.nan if now is None else now
            state[i] = now
        return out

    def step(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        history, averages, flags = ([list(h) for h in state.get[0]], list(state.get[1]), list(state.get[2])) if state.exists else ([[] for _ in metrics], [None] * len(decays), [])
        rows = pd.concat(list(batches)).sort_values(["ts", "rec_id"], kind="stable")
        values = {m: np.concatenate([np.array(h, float), rows[m].to_numpy(float, na_value=np.nan)]) for h, m in zip(history, metrics, strict=True)}
        found = averages_of(rows, averages)
        if framed:
            long = feature_matrix(values, np.array([len(values[metrics[0]])]), framed, points_per_day)
            found |= {f: x[len(x) - len(rows) :] for f, x in zip(framed, long, strict=True)}
        abnormal = np.zeros(len(rows), bool)
        for f, low, high in tests:  # a feature that is undefined (nan) passes both
            abnormal |= (found[f] < low) if low is not None else False
            abnormal |= (found[f] >= high) if high is not None else False
        held = np.concatenate([np.array(flags, bool), abnormal])
        upto = np.concatenate([[0], np.cumsum(held)])
        at = np.arange(len(flags), len(held))
        hits = upto[at + 1] - upto[np.maximum(at + 1 - y, 0)]
        before = np.concatenate([[upto[len(flags)] - upto[max(len(flags) - y, 0)] if len(flags) else -1], hits[:-1]])
        out = pd.DataFrame({"device": key[0], "rec_id": rows["rec_id"].to_numpy(), "ts": rows["ts"].to_numpy(), "abnormal": abnormal, "hits": hits, "marked": hits >= x, "dispatch": (hits >= x) & (before < x)})
        kept = [[None if v != v else float(v) for v in values[m][-most:]] for m in metrics]
        state.update((kept, averages, [bool(v) for v in held[-y:]]))
        if idle_minutes:
            state.setTimeoutDuration(idle_minutes * 60_000)
        yield out

    timeout = GroupStateTimeout.ProcessingTimeTimeout if idle_minutes else GroupStateTimeout.NoTimeout
    rows = stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["rec_id"]).select("device", "rec_id", "ts", *metrics)
    return rows.groupBy("device").applyInPandasWithState(step, "device long, rec_id long, ts timestamp, abnormal boolean, hits long, marked boolean, dispatch boolean", "history array<array<double>>, averages array<double>, flags array<boolean>", "append", timeout)


def windowed_rates(stream: DataFrame, size: str = "1 day", slide: str | None = None, delay: str = "1 day", by: Sequence[str] = ("node",)) -> DataFrame:
    """Records and abnormal records per tumbling or sliding window, final once the watermark has passed."""
    span = F.window("ts", size, slide) if slide else F.window("ts", size)
    out = stream.withWatermark("ts", delay).groupBy(span, *by).agg(F.count(F.lit(1)).alias("records"), F.sum(F.col("abnormal").cast("int")).alias("abnormal_records"))
    return out.select("window.start", "window.end", *by, "records", "abnormal_records")


def fault_sessions(marked: DataFrame, gap: str = "1 day", delay: str = "1 day") -> DataFrame:
    """Sessions of marked records per device: a streaming approximation of faults, closed by a silent gap."""
    span = F.session_window("ts", gap)
    rows = marked.where("marked").withWatermark("ts", delay)
    return rows.groupBy(span, "device").agg(F.count(F.lit(1)).alias("points"), F.max("hits").alias("peak")).select("device", F.col("session_window.start").alias("onset"), F.col("session_window.end").alias("end"), "points", "peak")


def tickets_after_dispatch(dispatches: DataFrame, tickets: DataFrame, within: str = "3 days", delay: str = "1 day") -> DataFrame:
    """Stream-stream interval join: tickets of a device's account that come within a time after its dispatch."""
    d = dispatches.where("dispatch").select(F.col("device").alias("account"), F.col("ts").alias("at")).withWatermark("at", delay).alias("d")
    t = tickets.select("ticket_id", F.col("account").alias("t_account"), F.col("created").alias("created")).withWatermark("created", delay).alias("t")
    return d.join(t, F.expr(f"account = t_account AND created >= at AND created < at + interval {within}")).select("account", "at", "ticket_id", "created")


def write_upserts(stream: DataFrame, path: str, checkpoint: str, key: Sequence[str] = ("device", "rec_id")):
    """Each batch as its own directory, named by batch: a replayed batch overwrites itself, so rows land exactly once."""

    def put(batch: DataFrame, number: int) -> None:
        batch.dropDuplicates(list(key)).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
