"""Token counts by the whole-token shortcut (see ``pretokens``): pre-tokens that are proved to be one
token each are counted as they are met, and only the rest is merged."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .pretokens import encoder


def _piece_counts(path: str, texts: list[str]) -> list[int]:
    from .pieces import codec

    return [len(i) for i in codec(path).library.encode(texts, out_type=int, num_threads=1)] if texts else []


def count_tokens(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: its id, n_bytes (UTF-8), n_tokens, as the vocabulary's library counts.

    No begin, end or added special tokens.  A null text is an empty one.  Vocabularies in .json go
    through ``PretokenEncoder``, those in .model through sentencepiece.
    """
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = rows.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if vocabulary.endswith(".model"):
                counts = _piece_counts(vocabulary, [t.as_py() or "" for t in b.column(1)])
            else:
                counts = list(encoder(vocabulary).counts(t.as_py() for t in b.column(1)))
            sizes = [len(t.as_buffer()) if t.is_valid else 0 for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sizes, pa.int64()), pa.array(counts, pa.int64())], ["id", "n_bytes", "n_tokens"])

    return rows.mapInArrow(run, f"id {kind}, n_bytes long, n_tokens long").withColumnRenamed("id", id_col)
