"""The solver as a stateful stream: a part is a key whose state is its block, its iterate and the last slab of each peer.

Slabs arrive as files. A micro-batch hands each part what has come for it; the part keeps the newest slab of each peer by its
stamp, makes one local step, and sends slabs. Structured Streaming has no cycles, so what is sent is written into the folder
that the source watches: data are a micro-batch old at least. A part's block is its first message, so it lives in the state
store and nowhere else. A master sums the parts' latest squared norms.
"""

from __future__ import annotations

import pickle
import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from overlapsolve.functions.solvers import factor, kept
from overlapsolve.operators.local import Block
from overlapsolve.plans.bsp import Supersteps
from overlapsolve.session import scratch
from overlapsolve.system import Config, Sys

MESSAGE = "dst int, src int, stamp long, vals array<double>, block binary"
OUT = "kind int, dst int, src int, stamp long, vals array<double>, ids array<long>, resid double"


def _step(name: str, cfg: Config):
    def of(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        block, w, seen, count = pickle.loads(state.get[0]) if state.exists else (None, None, {}, 0)
        for rows in batches:
            for r in rows.itertuples():
                if r.block is not None:
                    block = Block.of(pickle.loads(r.block))
                    w = np.zeros(block.n) if w is None else w
                elif r.stamp > seen.get(r.src, (-1, None))[0]:  # an older slab than the last one is late, and ignored
                    seen[r.src] = (r.stamp, np.array(r.vals, float))
        out = []
        if block is not None:
            s = block.slab(w)
            if count or seen or not len(block.peers):
                r = block.accumulated(s, {q: x for q, (_, x) in seen.items()})
                resid = float(r[block.owned] @ r[block.owned])
                w = w + kept((name, block.p, cfg.solver), lambda: factor(block.indptr, block.indices, block.data, cfg.solver, cfg.rtol)).solve(r)
                s = block.slab(w)
                out.append((0, block.p, block.p, count, w[block.owned].tolist(), block.ids[block.owned].tolist(), resid))
            count += 1
            out += [(1, q, block.p, count, v.tolist(), None, 0.0) for q, v in block.outgoing(s)]
            state.update((pickle.dumps((block, w, seen, count)),))
        yield pd.DataFrame(out, columns=[x.split()[0] for x in OUT.split(", ")])

    return of


def run_streaming(sys: Sys, cfg: Config = Config()) -> tuple[DataFrame, DataFrame]:
    """((i, x), history (p, iteration, resid)) of the one-level method; stops at the tolerance or after cfg.timeout_s."""
    spark, run = sys.entries.sparkSession, Supersteps(sys, cfg)
    folder = f"{scratch(spark)}/stream-{run.name}"
    # Blocks go into the stream as they lie on executors.
    pack = lambda batches: (pd.DataFrame([(r["p"], r["p"], 0, None, pickle.dumps(r)) for r in b.to_dict("records")], columns=["dst", "src", "stamp", "vals", "block"]) for b in batches)
    run.blocks.mapInPandas(pack, MESSAGE).write.mode("append").parquet(f"{folder}/slabs")
    parts = run.blocks.count()
    latest: dict[int, float] = {}

    def feed_back(batch: DataFrame, number: int) -> None:
        batch.persist()
        sent = batch.where("kind = 1").select("dst", "src", "stamp", "vals", F.lit(None).cast("binary").alias("block"))
        sent.coalesce(1).write.mode("append").parquet(f"{folder}/slabs")
        batch.where("kind = 0").select(F.lit(number).alias("batch"), F.col("dst").alias("p"), F.col("stamp").alias("iteration"), "ids", "vals", "resid").write.mode("append").parquet(f"{folder}/iterates")
        latest.update({r["dst"]: r["resid"] for r in batch.where("kind = 0").select("dst", "resid").collect()})  # one number a part
        batch.unpersist()

    slabs = spark.readStream.schema(MESSAGE).parquet(f"{folder}/slabs")
    moved = slabs.groupBy("dst").applyInPandasWithState(_step(run.name, cfg), OUT, "held binary", "update", GroupStateTimeout.NoTimeout)
    query = moved.writeStream.foreachBatch(feed_back).outputMode("update").option("checkpointLocation", f"{folder}/progress").start()
    begun = time.time()
    while query.isActive and time.time() - begun < cfg.timeout_s and not (len(latest) == parts and sum(latest.values()) < cfg.tol**2):
        time.sleep(0.05)
    failed = query.exception()
    query.stop()
    run.close()
    if failed is not None:
        raise failed
    seen = spark.read.parquet(f"{folder}/iterates")
    last = seen.groupBy("p").agg(F.max_by(F.struct("ids", "vals"), "iteration").alias("w"))
    u = last.select(F.explode(F.arrays_zip("w.ids", "w.vals")).alias("z")).select(F.col("z.ids").alias("i"), F.col("z.vals").alias("x"))
    return u, seen.select("p", "iteration", "resid")


# Loads by event time; all work on tables and on streams.


def _timed(events: DataFrame, delay: str) -> DataFrame:
    """A stream's watermark is on its event time, which must be a time with a zone."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay) if events.isStreaming else events


def hourly(events: DataFrame, delay: str = "2 hours") -> DataFrame:
    """(hour, x): values by tumbling hour; later events than `delay` are dropped from a stream."""
    timed = _timed(events, delay)
    return timed.groupBy(F.window("ts", "1 hour").alias("w")).agg(F.sum("value").alias("x")).select(F.col("w.start").alias("hour"), "x")


def sliding(events: DataFrame, length: str = "6 hours", step: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    """(start, x): mean values of overlapping windows."""
    timed = _timed(events, delay)
    return timed.groupBy(F.window("ts", length, step).alias("w")).agg(F.avg("value").alias("x")).select(F.col("w.start").alias("start"), "x")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "2 hours") -> DataFrame:
    """(user_id, start, events): runs of a user's events without a longer gap."""
    timed = _timed(events, delay)
    return timed.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("events")).select("user_id", F.col("w.start").alias("start"), "events")


def once(slabs: DataFrame, delay: str = "10 minutes") -> DataFrame:
    """Slabs (src, dst, stamp, ts, ...) without repeats of a stamp."""
    keys = ["src", "dst", "stamp"]
    return slabs.withWatermark("ts", delay).dropDuplicatesWithinWatermark(keys) if slabs.isStreaming else slabs.dropDuplicates(keys)


def answered(requests: DataFrame, corrections: DataFrame, within: str = "1 minute") -> DataFrame:
    """Requests (p, epoch, ts) with the correction of their epoch (epoch, ts, v0) that comes within the given time."""
    a, b = requests.alias("a"), corrections.alias("b")
    if requests.isStreaming:
        a, b = requests.withWatermark("ts", within).alias("a"), corrections.withWatermark("ts", within).alias("b")
    return a.join(b, F.expr(f"a.epoch = b.epoch and b.ts >= a.ts and b.ts <= a.ts + interval {within}")).select("a.p", "a.epoch", "b.v0")
