"""A keyed verifier over a stream: remembers how often each triple was met and rejected, and forgets idle ones.

It needs a state store that keeps column families (RocksDB), set when the session starts: spark.sql.streaming.stateStore.providerClass =
org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider.
"""

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

OUTPUT = "triple string, seen long, rejected long, verdict string"


class Verifier(StatefulProcessor):
    """A triple is settled once it was met ``votes`` times with fewer rejections than acceptances; idle memory expires after ttl_ms."""

    def __init__(self, votes: int = 2, ttl_ms: int = 3_600_000):
        self.votes, self.ttl_ms = votes, ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.memory = handle.getValueState("memory", "seen long, rejected long", self.ttl_ms)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        seen, rejected = self.memory.get() if self.memory.exists() else (0, 0)
        for pdf in rows:
            seen += len(pdf)
            rejected += int((~pdf["ok"]).sum())
        self.memory.update((seen, rejected))
        verdict = "open" if seen < self.votes else "accepted" if 2 * rejected < seen else "rejected"
        yield pd.DataFrame([(key[0], seen, rejected, verdict)], columns=["triple", "seen", "rejected", "verdict"])

    def close(self) -> None:
        pass


def verifier_state(judged: DataFrame, **options) -> DataFrame:
    """judged: triple string, ok boolean, as a stream."""
    return judged.groupBy("triple").transformWithStateInPandas(statefulProcessor=Verifier(**options), outputStructType=OUTPUT, outputMode="Update", timeMode="ProcessingTime")
