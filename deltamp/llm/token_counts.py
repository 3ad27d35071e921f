"""Token counts of whole texts through the compiled transducers of :mod:`tokenfsm`.

Defined cases: a null text counts as empty (0 bytes, 0 tokens); an added token's string inside a text is
one token, as in the library; very long texts are split and counted part by part; repeated rows are
counted alike; other columns are kept, those called like the results are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator

import public_tokenizers
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import tokenfsm
from .common import read

LIMIT = 1024


def count_tokens(docs: DataFrame, path: str, text: str = "text", out: str = "n_tokens") -> DataFrame:
    @F.arrow_udf("bigint")
    def counted(parts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for part in parts:
            yield pa.array(tokenfsm.count(part, path), pa.int64())

    kept = [F.col(f"`{c}`") for c in docs.columns if c != out]
    return docs.select(*kept, counted(F.col(f"`{text}`")).alias(out))


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    n_bytes = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes")
    return count_tokens(docs, public_tokenizers.path("byte_bpe_50k.json")).select("doc_id", n_bytes, "n_tokens", (F.col("n_tokens") > LIMIT).alias("over_limit"))
