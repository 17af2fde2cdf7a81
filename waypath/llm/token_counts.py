"""Token counts by the whole-token shortcut."""

from __future__ import annotations

import pyarrow as pa
import public_tokenizers
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tokens import WORD_FILE, loaded, prove_whole_tokens

LIMIT = 2048


def token_counts(docs: DataFrame, path: str | None = None, limit: int = LIMIT) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row of docs(doc_id, text, ...).

    Which vocabulary strings encode alone as one token is proven once on the driver (the
    set is bounded by the vocabulary) and broadcast.  A pre-token in the set counts one;
    only the rest is merged.  Null and empty texts have no bytes and no tokens; repeated
    rows give repeated results; a null doc_id stays null; other columns are ignored.  An
    empty table gives an empty result.  Long texts are counted whole.
    """
    path = path or public_tokenizers.path(WORD_FILE)
    whole = docs.sparkSession.sparkContext.broadcast(prove_whole_tokens(path))

    def count(batches):
        bpe = loaded(path, whole.value)
        for b in batches:
            texts = b.column(1).to_pylist()
            yield pa.RecordBatch.from_arrays([
                b.column(0),
                pa.array([len(t.encode()) for t in texts], pa.int64()),
                pa.array([bpe.count(t) for t in texts], pa.int64()),
            ], ["doc_id", "n_bytes", "n_tokens"])

    out = docs.select(F.col("doc_id").cast("long"), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(count, "doc_id long, n_bytes long, n_tokens long")
    return out.withColumn("over_limit", F.col("n_tokens") > limit)
