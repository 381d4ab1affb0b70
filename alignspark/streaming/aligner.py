"""The stateful aligner: cells arrive in any order between series, tuples leave once nothing later can change them.

State per group: the cells still needed, the open clique, the cells of recent
winners and the next lead. A lead is folded once every series has passed it by
the look-ahead bound, so the stream's tuples equal the batch result. A row with
sid 0 marks the end of a group's recording and flushes it; with ``idle_ms`` a
group that has been silent for so long is flushed too, so that a series which
stalls does not hold its group's state for ever. Cells behind the next lead's
reach come too late to be aligned: they leave as rows of kind ``late`` (sid and
row number in x), never silently.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from alignspark.operators import candidates as C
from alignspark.operators.conflicts import shared_path
from alignspark.operators.fold import _choose, expectation_scores, tie_key
from alignspark.params import AlignParams
from alignspark.plans.blocks import _run

OUT = "grp string, kind string, x array<long>, w_fp long"


def stepper(m: int, p: AlignParams, method: str, idle_ms: int | None = None):
    """The function for applyInPandasWithState."""

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = json.loads(state.get[0]) if state.exists else {"cells": [], "fold": {"clique": [], "won": []}, "next": 1}
        cells = {(c[0], c[1]): c for c in held["cells"]}
        ended = state.hasTimedOut
        floor_ = held["next"] - 3 * p.beta - 1
        late: list[list[int]] = []
        for pdf in parts:
            ended |= bool((pdf["sid"] == 0).any())
            pdf = pdf[pdf["sid"] > 0]
            behind = pdf["idx"] < floor_
            late += pdf.loc[behind, ["sid", "idx"]].to_numpy().tolist()
            own = pdf[~behind]
            ts, val = own["ts_us"].astype(object).where(own["ts_us"].notna(), None), own["val"].astype(object).where(own["val"].notna(), None)
            for sid, idx, t, v in zip(own["sid"].tolist(), own["idx"].tolist(), ts.tolist(), val.tolist()):
                cells[sid, idx] = (sid, idx, None if t is None else int(t), v)
        seen = [max((i for s, i in cells if s == j), default=0) for j in range(1, m + 1)]
        reach = max(seen) if ended else min(seen) - 4 * p.beta - 2
        chosen: list[tuple[list[int], int]] = []
        if reach >= held["next"] or ended:
            rows = sorted(cells.values(), key=lambda c: (c[0], c[1]))
            frame = pd.DataFrame(rows, columns=["sid", "idx", "ts_us", "val"])
            times, _, has, first = C.matrices(frame, m, p.lam_mode == "cell")
            low = max(first, held["next"] - 2 * p.beta - 1)
            x, lam, _ = C.expand_block(times, has, m, p.theta, p.beta, low, first + len(times) - 1, first, p.cap)
            _, _, w_fp = C.numpy_weights(x, lam, p)
            got, left, _ = _run(x, w_fp, p, method, held["fold"], held["next"], reach)
            if ended and left["clique"]:
                where = {tuple(r): k for k, r in enumerate(x.tolist())}
                clique = [where[tuple(r)] for r in left["clique"]]
                score = expectation_scores(x, w_fp, clique, p) if method == "expectation" and len(clique) > 1 else w_fp[clique]
                got.append(_choose(clique, score, tie_key(x, p)))
                left = {"clique": [], "won": []}
            chosen = [(x[k].tolist(), int(w_fp[k])) for k in got]
            held["fold"], held["next"] = left, reach + 1
            keep = min([r[0] for r in left["clique"]], default=reach + 1) - 3 * p.beta - 1
            cells = {k: c for k, c in cells.items() if k[1] >= keep}
        held["cells"] = list(cells.values())
        if ended:
            state.remove() if state.exists else None
        else:
            state.update((json.dumps(held),))
            if idle_ms:
                state.setTimeoutDuration(idle_ms)
        out = [("tuple", x, w) for x, w in chosen] + [("late", x, None) for x in late]
        yield pd.DataFrame({"grp": [key[0]] * len(out), "kind": [o[0] for o in out], "x": pd.Series([o[1] for o in out], dtype=object), "w_fp": pd.array([o[2] for o in out], dtype="Int64")})

    return step


def align_stream(cells: DataFrame, m: int, p: AlignParams, method: str = "greedy", idle_ms: int | None = None) -> DataFrame:
    """A streaming frame of cells (grp, sid, idx, ts_us, val) to a streaming frame of tuples and late cells."""
    timeout = GroupStateTimeout.ProcessingTimeTimeout if idle_ms else GroupStateTimeout.NoTimeout
    return cells.groupBy("grp").applyInPandasWithState(stepper(m, p, method, idle_ms), OUT, "held string", "append", timeout)


def replay(spark: SparkSession, series: DataFrame, m: int, p: AlignParams, method: str = "greedy", pieces: int = 4) -> DataFrame:
    """Plays a series through the aligner piece by piece, by row number, then the end marks; tuples and late cells."""
    top = shared_path(spark, "replay")
    n = series.agg(F.max("idx")).first()[0] or 1
    ends = series.select("grp").distinct().select("grp", F.lit(0).alias("sid"), F.lit(0).cast("long").alias("idx"), F.lit(None).cast("long").alias("ts_us"), F.lit(None).cast("double").alias("val"))
    parts = [series.where((F.col("idx") * pieces > k * n) & (F.col("idx") * pieces <= (k + 1) * n)).select("grp", "sid", "idx", "ts_us", "val") for k in range(pieces)]
    for part in [*parts, ends]:
        part.write.mode("append").parquet(f"{top}/in")
        cells = spark.readStream.schema("grp string, sid int, idx long, ts_us long, val double").parquet(f"{top}/in")
        run = align_stream(cells, m, p, method).writeStream.outputMode("append").option("checkpointLocation", f"{top}/state").trigger(availableNow=True).format("parquet").start(f"{top}/out")
        run.awaitTermination()
    return spark.read.schema(OUT).parquet(f"{top}/out")
