"""First-seen keys of a stream with the filter as keyed state: one subfilter a state, kept by Spark's state store.

The counterpart of :class:`fpfilter.streaming.membership.OnlineFilter` without tables between batches: rows go to
their subfilter, which probes them, lets one row of each new entry through and stores its words again. Many subfilters
keep each state small. A false positive may hold a new key back (at about the filter's rate); no entry passes twice.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from fpfilter.functions import lanes
from fpfilter.operators import cuckoo
from fpfilter.operators.filters import fresh, sub_of, with_mixed
from fpfilter.operators.spec import FilterSpec, sized

#: The store that such states need; a setting of the session that may be changed at any time.
STORE = ("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")


class _Subfilter(StatefulProcessor):
    def __init__(self, spec: FilterSpec, mixed: str, names: list[str]):
        self.spec, self.mixed, self.names = spec, mixed, names

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.words = handle.getValueState("words", "words binary")

    def handleInputRows(self, key: Any, rows: Iterator[pd.DataFrame], timerValues: Any) -> Iterator[pd.DataFrame]:
        spec = self.spec
        words = np.frombuffer(self.words.get()[0], np.uint64) if self.words.exists() else lanes.pack(np.zeros(spec.n_slots, np.uint64), spec.slot_bits)
        for frame in rows:
            h = frame[self.mixed].to_numpy(np.int64).view(np.uint64)
            new = np.flatnonzero(~cuckoo.contains(words, h, spec))
            if not len(new):
                continue
            _, first = np.unique(np.stack(cuckoo.entries(h[new], spec), 1), axis=0, return_index=True)
            new = new[np.sort(first)]
            words, rest, _ = cuckoo.insert_free(words, h[new], spec)
            if len(rest):
                words, stats = cuckoo.build(rest, spec, lanes.unpack(words, spec.n_slots, spec.slot_bits))
                if stats["status"] != "ok":
                    raise RuntimeError("a subfilter is full: start a new generation and probe both")
            yield frame.iloc[new][self.names]
        self.words.update((words.tobytes(),))

    def close(self) -> None:
        pass


def first_seen(stream: DataFrame, key: str, spec: FilterSpec, n: int) -> DataFrame:
    """The rows of ``stream`` whose non-null ``key`` (a long) was not seen before, one of each entry of the filter.

    ``n`` is the number of keys to size for; the session must use :data:`STORE`. Batch tables work as well as streams.
    """
    spec = spec if spec.n_addr else sized(spec, n)
    mixed, sub = fresh(stream, "h", "sub")
    rows = with_mixed(stream.where(F.col(key).isNotNull()), F.col(key), spec, mixed)
    rows = rows.withColumn(sub, sub_of(F.col(mixed), spec).cast("long"))
    return rows.groupBy(sub).transformWithStateInPandas(_Subfilter(spec, mixed, stream.columns), stream.schema, "append", "none")
