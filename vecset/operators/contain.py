"""Which texts hold which passages."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.limits import driver_table


def contained(texts: DataFrame, passages: DataFrame) -> DataFrame:
    """(query_id, set_id): every passage with every text that holds it, each pair once. texts: (id, text); passages: (id, text), a stated
    set of a checked size. One automaton of all passages goes through each text once. Null texts hold nothing; null and empty passages
    are left out."""
    text_id, passage_id = texts.columns[0], passages.columns[0]
    asked = driver_table(passages.where(F.col(passages.columns[1]).isNotNull() & (F.col(passages.columns[1]) != "")))
    named: dict[str, list[int]] = {}
    for i, p in zip(asked.column(0).to_pylist(), asked.column(1).to_pylist(), strict=True):
        named.setdefault(p, []).append(i)
    held = texts.sparkSession.sparkContext.broadcast(named)

    def run(batches):
        import ahocorasick

        machine = ahocorasick.Automaton()
        for p in held.value:
            machine.add_word(p, p)
        if held.value:
            machine.make_automaton()
        for batch in batches:
            q, s = [], []
            for i, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True) if held.value else ():
                for p in {p for _, p in machine.iter(text or "")}:
                    q += held.value[p]
                    s += [i] * len(held.value[p])
            yield pa.RecordBatch.from_arrays([pa.array(q, pa.int64()), pa.array(s, pa.int64())], names=["query_id", "set_id"])

    return texts.select(F.col(text_id).cast("long").alias("i"), F.col(texts.columns[1]).alias("t")).mapInArrow(run, "query_id long, set_id long")
