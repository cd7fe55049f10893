"""Token counts by heap-and-linked-list byte-pair merging; no identifiers are made.

The file is a tokenizers JSON (byte-level BPE with word ends), read by words.MergeCounter. Defined results: null text counts 0 tokens and 0 bytes; extra columns
are ignored; repeated rows keep a row each; nothing is shuffled.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .words import end_of_task, merge_counter


def token_counts(docs: DataFrame, tokenizer: str, limit: int = 2048) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit of every whole text."""

    done = end_of_task

    def run(batches):
        counter = merge_counter(tokenizer)
        for b in batches:
            for k in range(0, b.num_rows, 512):
                part = b.slice(k, 512)
                n = [counter.count(t) for t in part.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())], ["doc_id", "n_bytes", "n_tokens", "over_limit"])
        done()

    src = docs.select(F.col("doc_id").cast("long"), F.coalesce(F.octet_length("text"), F.lit(0)).cast("long"), "text")
    return src.mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
