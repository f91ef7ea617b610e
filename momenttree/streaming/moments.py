"""Dynamic collections: additive moment numerators, session documents and stateful bags over streams of events.

First and second moments are means of per-document terms, so their numerators and the number of documents add up over
windows and batches; the core of the third moment needs the current whitener, hence bags are kept until it is made.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momenttree.runtime import shared_dir, ship

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, directory: str, files_per_batch: int = 1) -> DataFrame:
    """events as a file stream."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).option("pathGlobFilter", "events.parquet").parquet(directory)


def run_to_table(stream: DataFrame, name: str, mode: str = "append", transform: Callable | None = None) -> DataFrame:
    """Runs a stream over what is there, into Parquet in the shared folder, and reads the result.

    complete and update modes go through foreachBatch: each batch overwrites its own folder (so a repeated batch does
    no harm); complete keeps the last batch.
    """
    spark = stream.sparkSession
    base = f"{shared_dir(spark).rstrip('/')}/{name}_{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/log").trigger(availableNow=True)
    last = {"batch": None}
    if mode == "append":
        query = writer.format("parquet").option("path", f"{base}/out").start()
    else:

        def put(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{base}/out/batch={number}")
            last["batch"] = number

        query = writer.foreachBatch(put).start()
    query.awaitTermination()
    if query.exception():
        raise query.exception()
    out = spark.read.schema(stream.schema).parquet(f"{base}/out" if mode == "append" else f"{base}/out/batch={last['batch']}")
    return transform(out) if transform else out


def late_rows(query) -> int:
    """Rows that a finished streaming query left out because they came behind its watermark."""
    return sum(int(op["numRowsDroppedByWatermark"]) for progress in query.recentProgress for op in progress["stateOperators"])


def word_of(events: DataFrame) -> DataFrame:
    """event_id, ts, user_id, word: event type with a bucket of its property."""
    bucket = F.floor(F.get_json_object("props", "$.k").cast("int") / 10)
    return events.select("event_id", "ts", "user_id", F.concat_ws("_", "event_type", bucket.cast("string")).alias("word"))


def tumbling_numerators(words: DataFrame, length: str = "1 day", late: str = "1 hour") -> DataFrame:
    """start, word, n, users: occurrences and an estimate of the users of each word and window, events later than `late` left out.

    With events as they come, n is the numerator of a first moment whose documents are windows.
    """
    out = words.withWatermark("ts", late).groupBy(F.window("ts", length).alias("w"), "word").agg(F.count("*").alias("n"))
    return out.select(F.col("w.start").alias("start"), "word", "n")


def sliding_counts(words: DataFrame, length: str = "1 day", slide: str = "12 hours", late: str = "1 hour") -> DataFrame:
    out = words.withWatermark("ts", late).groupBy(F.window("ts", length, slide).alias("w")).agg(F.count("*").alias("n"))
    return out.select(F.col("w.start").alias("start"), "n")


def session_docs(words: DataFrame, gap: str = "2 hours", late: str = "1 hour") -> DataFrame:
    """Users' sessions as documents: user_id, start, n."""
    out = words.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return out.select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(words: DataFrame, late: str = "1 hour") -> DataFrame:
    return words.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def stateful_bags(words: DataFrame, *, every: int = 50) -> DataFrame:
    """user_id, part, words, counts, n: a bag of each user's next `every` events, kept in keyed state between batches.

    A user's state is at most `every` words.  After each batch the open rest is shown too, as a bag of n < every events
    that a later one of the same part replaces: latest_bags() keeps the last of each.
    """
    ship(words.sparkSession)

    def update(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        part, held = state.get if state.exists else (0, [])
        held = list(held)
        rows = []

        def show() -> None:
            counts = pd.Series(held).value_counts().sort_index()
            rows.append((key[0], part, counts.index.tolist(), counts.tolist(), len(held)))

        for word in pd.concat(list(frames)).sort_values(["ts", "event_id"])["word"]:
            held.append(word)
            if len(held) == every:
                show()
                part, held = part + 1, []
        if held:
            show()
        state.update((part, held))
        yield pd.DataFrame(rows, columns=["user_id", "part", "words", "counts", "n"])

    return words.groupBy("user_id").applyInPandasWithState(update, "user_id bigint, part int, words array<string>, counts array<bigint>, n bigint", "part int, held array<string>", "append", "NoTimeout")


def latest_bags(shown: DataFrame) -> DataFrame:
    """user_id, part, words, counts: of each part the bag with the most events."""
    return shown.groupBy("user_id", "part").agg(F.max_by(F.struct("words", "counts"), "n").alias("b")).select("user_id", "part", "b.words", "b.counts")


class MomentState:
    """Running numerators of M1 and E2 over batches of bags; drift says when the tree should be made anew."""

    def __init__(self, v: int):
        import numpy as np

        self.v, self.n = v, 0.0
        self.m1, self.e2 = np.zeros(v), np.zeros((v, v))

    def add(self, bags: DataFrame) -> None:
        from momenttree.operators.moments import moments_of

        found = moments_of(bags, self.v)
        if "o" in found:
            part = found["o"]
            self.m1 += part.m1 * part.n_docs
            self.e2 += part.e2 * part.n_docs
            self.n += part.n_docs

    def moments(self):
        return self.m1 / max(self.n, 1), self.e2 / max(self.n, 1)

    def drift(self, reference) -> float:
        """L1 distance of the current first moment from a reference."""
        import numpy as np

        return float(np.abs(self.moments()[0] - reference).sum())
