"""Token counts by a two-tier lookup inside map tasks."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankgrid.llm.pretokens import broadcast_vocabulary, encoder
from rankgrid.llm.textblocks import map_arrow, small_batches


def texts_of(batch: pa.RecordBatch) -> list[str]:
    return pc.fill_null(batch.column("text"), "").to_pylist()


def id_and_text(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def token_counts(docs: DataFrame, tokenizer: str, limit: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: doc_id, n_bytes, n_tokens, over_limit (n_tokens > limit).

    Null and empty texts have 0 bytes and 0 tokens; repeated rows are counted each; a null id stays null; an empty table
    gives no rows; long texts are read whole in windows; other columns are not read.
    """
    shared = broadcast_vocabulary(docs.sparkSession, tokenizer)

    def count(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = encoder(shared.value)
        for b in small_batches(batches, "text"):
            n = tokens.counts(texts_of(b))
            size = pc.fill_null(pc.binary_length(b.column("text")), 0).cast(pa.int64())
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), size, pa.array(n), pa.array(np.greater(n, limit))], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return map_arrow(id_and_text(docs, id_col, text_col), count, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
