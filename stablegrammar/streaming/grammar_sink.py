"""Grammars of streams: batches are buffer grammars, the sink a directory that takes only rules it lacks."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stablegrammar.functions.hashing import HashFamily, make_family
from stablegrammar.operators.build import breaks_numpy, build_grammar
from stablegrammar.sources.io import append_to_sink


def grammar_sink(stream: DataFrame, path: str, checkpoint: str, family: HashFamily | None = None, once: bool = True):
    """StreamingQuery that keeps the grammar of strings(string_id, text) at `path`; a replayed batch changes nothing."""
    family = family or make_family()
    writer = stream.writeStream.foreachBatch(lambda df, i: append_to_sink(build_grammar(df, family), path, i)).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if once else writer).start()


def window_sequences(events: DataFrame, types: list[str], size: str = "1 hour", slide: str | None = None, gap: str | None = None, watermark: str = "1 hour") -> DataFrame:
    """One string of event codes per user and window (tumbling, sliding or session), for batches and streams; rows beyond the watermark go."""
    code = F.array_position(F.array(*map(F.lit, types)), F.col("event_type")).cast("int")
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if events.isStreaming:
        timed = timed.withWatermark("ts", watermark)
    window = F.session_window("ts", gap) if gap else F.window("ts", size, slide) if slide else F.window("ts", size)
    seq = F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", code.alias("c")))), lambda x: x["c"])
    return timed.groupBy("user_id", window.alias("w")).agg(seq.alias("syms"), F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "syms")


def stateful_phrases(events: DataFrame, family: HashFamily | None = None) -> DataFrame:
    """(user_id, start, len, fp) of level-1 phrases as soon as later events can't change them; a user's unfinished tail stays in state.

    events(user_id, code): a break is final once the first different fingerprint after its run is known.
    """
    family = family or make_family()
    h0, h1 = family[0], family[1]

    def finish(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        base, tail = state.get if state.exists else (0, [])
        for pdf in batches:
            tail = [*tail, *pdf["code"].tolist()]
        fps = (h0.a * np.array(tail, np.int64) + h0.b) % h0.p % h0.m if tail else np.zeros(0, np.int64)
        out = []
        if len(fps):
            at = np.flatnonzero(breaks_numpy(fps, np.array([0]))).tolist()
            for a, b in zip(at, at[1:], strict=False):
                total = 0
                for f in reversed(fps[a:b].tolist()):
                    total = (total * h1.c + f) % h1.p
                out.append((key[0], base + a + 1, b - a, (h1.a * total + h1.b) % h1.p % h1.m))
            # the tail keeps the element before its first one's run, or a break at its start would be lost
            base, tail = base + at[-1], tail[at[-1] :]
        state.update((base, [int(x) for x in tail]))
        yield pd.DataFrame(out, columns=["user_id", "start", "len", "fp"])

    return events.groupBy("user_id").applyInPandasWithState(finish, "user_id long, start long, len long, fp long", "base long, tail array<int>", "append", "NoTimeout")
