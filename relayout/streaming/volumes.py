"""Volumes of a stream: parcels by time window, sessions, re-sent events, and the assembly of tiles as pieces arrive.

The window functions take a batch or a streaming DataFrame alike; events' times are TIMESTAMP (a watermark needs that).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from relayout.plans.relabel import find_relabeling

TYPES = ("click", "purchase", "view")


def events(df: DataFrame, late: str | None = None) -> DataFrame:
    """(ts, src, dst, user_id, event_id): the user's bucket sends to the event type; late: watermark, on streams."""
    kind = F.coalesce(F.create_map(*(F.lit(x) for kv in ((t, i) for i, t in enumerate(TYPES)) for x in kv))[F.col("event_type")], F.lit(len(TYPES)))
    out = df.select(F.col("ts").cast("timestamp").alias("ts"), F.pmod("user_id", F.lit(5)).cast("int").alias("src"), kind.cast("int").alias("dst"), "user_id", "event_id")
    return out.withWatermark("ts", late) if late else out


def windowed(rows: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """(start, src, dst, n): parcels of tumbling or sliding windows."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return rows.groupBy(w.alias("w"), "src", "dst").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "src", "dst", "n")


def sessions(rows: DataFrame, gap: str) -> DataFrame:
    """(user_id, start, n): events of a user that are less than gap apart."""
    return rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def once(rows: DataFrame) -> DataFrame:
    """Each event_id once, within the watermark; rows must carry one."""
    return rows.dropDuplicatesWithinWatermark(["event_id"])


def answered(asks: DataFrame, replies: DataFrame, within: str) -> DataFrame:
    """Of each ask (user_id, ts) the replies (user_id, ts) of that user within the interval; both with a watermark."""
    a, b = asks.select(F.col("user_id").alias("user"), F.col("ts").alias("asked")), replies.select("user_id", F.col("ts").alias("replied"))
    return a.join(b, F.expr(f"user = user_id AND replied >= asked AND replied <= asked + INTERVAL {within}"))


def refresh(n: int, keep: dict, margin: float = 0.05) -> Callable[[DataFrame, int], None]:
    """A foreachBatch sink: batches (src, dst, vol) add to keep["parcels"]; the relabeling in keep["sigma"] changes only if
    a new one saves ``margin`` more than it does (hysteresis)."""

    def step(batch: DataFrame, _: int) -> None:
        held = keep.setdefault("parcels", {})
        for r in batch.groupBy("src", "dst").agg(F.sum("vol").alias("v")).collect():  # sites squared rows
            held[r["src"], r["dst"]] = held.get((r["src"], r["dst"]), 0) + r["v"]
        rows = [(s, d, 1, v) for (s, d), v in held.items()]
        if not rows:
            return
        plan = find_relabeling(batch.sparkSession.createDataFrame(rows, "src int, dst int, n_pieces long, vol long"), n=n)
        now = keep.get("sigma", list(range(n)))
        cost = sum(v for (s, d), v in held.items() if s != now[d])
        if cost and (cost - plan.after) / cost > margin:
            keep["sigma"] = plan.sigma

    return step


def assembled(pieces: DataFrame, side: int, area: int) -> DataFrame:
    """(bi, bj, cells, total, data): square tiles of ``area`` cells, each given out when its last cell arrives, with all its
    cells row by row. pieces: (i, j, v), a streaming DataFrame in any order; a cell that comes again replaces the one
    before it. State is kept only for tiles that are not complete: what has come of them, as places and values."""

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        places, values = state.get if state.exists else ([], [])
        held = dict(zip(places, values, strict=True))
        for f in frames:
            held.update(zip(f["place"].tolist(), f["v"].tolist(), strict=True))
        if len(held) >= area:
            if state.exists:
                state.remove()
            data = [held[k] for k in sorted(held)]
            yield pd.DataFrame({"bi": [key[0]], "bj": [key[1]], "cells": [len(data)], "total": [sum(data)], "data": [data]})
        else:
            state.update((list(held), list(held.values())))

    block = lambda c: ((F.col(c) - F.pmod(c, F.lit(side))) / side).cast("long")
    place = F.pmod("i", F.lit(side)) * side + F.pmod("j", F.lit(side))
    keyed = pieces.select(block("i").alias("bi"), block("j").alias("bj"), place.cast("long").alias("place"), "v")
    return keyed.groupBy("bi", "bj").applyInPandasWithState(run, "bi long, bj long, cells long, total long, data array<long>", "places array<long>, vals array<long>", "append", GroupStateTimeout.NoTimeout)
