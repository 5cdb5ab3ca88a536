"""BPE encoding and decoding of whole texts by the trie traversal of ``trie_bpe``.

Defined cases: null and empty texts give no ids and the empty string; texts of any
length are encoded whole; extra columns stay outside the result.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mlcurate.llm import tokens
from mlcurate.session import prepare


def encode(docs: DataFrame, vocab: str | None = None, digests: bool = False) -> DataFrame:
    """(doc_id, n_tokens, ids, decoded), or with ``digests`` SHA-256 of both in place of ids and decoded text."""
    prepare(docs.sparkSession)
    vocab = vocab or tokens.default_path()

    def run(batches):
        import hashlib

        import pyarrow as pa

        t = tokens.table(vocab, "trie", decoded=True)
        for b in batches:
            for i, j in tokens.slices(b.column(1)):
                got = t.batch(b.column(1)[i:j])
                said, raw, ends = t.spoken(got), got.ids.astype("<u4"), np.cumsum(got.lens).tolist()
                own = [raw[x:y] for x, y in zip([0, *ends[:-1]], ends, strict=True)]
                if digests:
                    own = [hashlib.sha256(x).hexdigest() for x in own]
                    said = [hashlib.sha256(x.as_buffer()).hexdigest() for x in said]
                yield pa.RecordBatch.from_arrays([b.column(0)[i:j], pa.array(got.lens, pa.int64()), pa.array(own, pa.string() if digests else pa.list_(pa.int32())), pa.array(said, pa.string())], names)

    names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"] if digests else ["doc_id", "n_tokens", "ids", "decoded"]
    schema = "doc_id long, n_tokens long, " + ("ids_sha256 string, decoded_sha256 string" if digests else "ids array<int>, decoded string")
    return docs.select(F.col("doc_id").cast("long"), F.col("text").alias("__text")).mapInArrow(run, schema)


def decode(ids: DataFrame, vocab: str | None = None) -> DataFrame:
    """(doc_id, text) from (doc_id, ids array<int>), as the library decodes with special tokens kept: tokens joined by spaces."""
    prepare(ids.sparkSession)
    vocab = vocab or tokens.default_path()

    def run(batches):
        import pyarrow as pa

        t = tokens.table(vocab, "trie", decoded=True).encoder.tokens
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([" ".join([t[i] for i in x or ()]) for x in b.column(1).to_pylist()], pa.string())], ["doc_id", "text"])

    return ids.select(F.col("doc_id").cast("long"), "ids").mapInArrow(run, "doc_id long, text string")
