"""Token counts: lengths only, in Arrow batches balanced by bytes."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_values
from .tokens import counter

#: The file of the public tokenizer, and the most tokens that a context takes.
MODEL, LIMIT = "piece_bpe_32k.model", 4096


def count_tokens(docs: DataFrame, text: str = "text", model: str = MODEL, limit: int = LIMIT, batch_bytes: int = 2_000_000) -> DataFrame:
    """Adds n_bytes, n_tokens and over_limit to every row of ``docs``; columns with these names are replaced.

    A null text counts as empty: 0 bytes, 0 tokens, not over the limit. Rows, their order in a partition and all
    other columns stay. Only texts go to Python, which returns one number for each; ids never leave the worker.
    """

    def each(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        count = counter(model)
        yield from text_values(texts, lambda ts: pa.array(count(ts), pa.int64()), batch_bytes)

    out = docs.drop("n_bytes", "over_limit").withColumn("n_tokens", F.arrow_udf(each, "long")(F.col(text)))
    return out.withColumn("n_bytes", F.coalesce(F.octet_length(text), F.lit(0)).cast("long")).withColumn("over_limit", F.col("n_tokens") > limit)
