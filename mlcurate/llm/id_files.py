"""Token-id files: whole documents as ids, in ascending doc_id order, coded by ``range_coder``.

A file set is a Parquet table in any store that Spark writes to; each row is one
segment: the documents it holds, their lengths, and the coded ids. Rows are written
by committed tasks only, so a lost executor leaves no half file behind.

Defined cases: null and empty texts hold the end id alone; rows with a null doc_id
come first; repeated doc_ids keep all their rows, shorter texts first, then in order of
a hash, so starts are determined; an empty table gives no rows;
extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mlcurate import session
from mlcurate.llm import range_coder, tokens
from mlcurate.session import prepare

#: Ids that a segment takes before it is closed at a document's end; 16 bits hold each id.
SEGMENT = 3_000_000
_SCHEMA = "part int, seq int, first_doc long, n_docs long, n_ids long, docs binary, nulls binary, lengths binary, payload binary"


def write(docs: DataFrame, path: str, vocab: str | None = None, end_id: int = 2) -> None:
    """Encode every whole text and write the file set."""
    prepare(docs.sparkSession)
    vocab = vocab or tokens.default_path()

    def segments(batches):
        import numpy as np
        import pyarrow as pa
        from pyspark import TaskContext

        t, part = tokens.table(vocab), TaskContext.get().partitionId()
        ids: list[np.ndarray] = []
        names: list = []
        lens: list[np.ndarray] = []
        held = seq = 0

        def close():
            a = np.array([0 if x is None else x for x in names], "<i8")
            flat = np.concatenate(ids) if ids else np.zeros(0, np.uint16)
            row = [part, seq, names[0], len(names), len(flat), a.tobytes(), np.array([x is None for x in names], np.uint8).tobytes(), np.concatenate(lens).astype("<u4").tobytes(), range_coder.encode(flat)]
            types = [pa.int32(), pa.int32(), *[pa.int64()] * 3, *[pa.binary()] * 4]
            return pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(row, types, strict=True)], [c.split()[0] for c in _SCHEMA.split(", ")])

        for b in batches:
            keys, texts = b.column(0).to_pylist(), b.column(1)
            for i, j in tokens.slices(texts):
                coded = t.batch(texts[i:j])
                n = coded.lens
                got = np.insert(coded.ids, np.cumsum(n), end_id)
                names += keys[i:j]
                ids.append(got.astype(np.uint16))
                lens.append(n + 1)
                held += len(got)
                if held >= SEGMENT:
                    yield close()
                    seq, held, ids, names, lens = seq + 1, 0, [], [], []
        if names:
            yield close()

    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("__text"))
    order = ["doc_id", F.length("__text"), F.xxhash64("__text"), "__text"]  # ties: shorter texts first, then by hash
    ordered = ordered.repartitionByRange(*order).sortWithinPartitions(*order)
    ordered.mapInArrow(segments, _SCHEMA).write.parquet(path)


def read(spark, path: str) -> DataFrame:
    """(doc_id, start, ids) of every document, decoded from the files; ids is little-endian uint32 binary."""
    return _rows(spark, path, False)


def digest(spark, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document, from the decoded files."""
    return _rows(spark, path, True)


def _rows(spark, path: str, digest_only: bool) -> DataFrame:
    prepare(spark)
    files = spark.read.schema(_SCHEMA).parquet(path)
    # one small row per segment of some millions of ids
    begins, total = {}, 0
    for r in sorted(files.select("part", "seq", "n_ids").collect()):
        begins[(r.part, r.seq)] = total
        total += r.n_ids

    def decode(batches):
        import zlib

        import numpy as np
        import pyarrow as pa

        for b in batches:
            for r in b.to_pylist():
                ids = range_coder.decode(r["payload"]).astype("<u4")
                names, null = np.frombuffer(r["docs"], "<i8").tolist(), np.frombuffer(r["nulls"], np.uint8).tolist()
                n = np.frombuffer(r["lengths"], "<u4").astype(np.int64)
                ends = np.cumsum(n)
                start = begins[(r["part"], r["seq"])] + ends - n
                raw, cuts = ids.tobytes(), (ends * 4).tolist()
                each = [raw[a:z] for a, z in zip([0, *cuts[:-1]], cuts, strict=True)]
                cols = [pa.array([None if z else x for x, z in zip(names, null, strict=True)], pa.int64()), pa.array(start, pa.int64())]
                cols += [pa.array(n, pa.int64()), pa.array([zlib.crc32(x) for x in each], pa.int64())] if digest_only else [pa.array(each, pa.binary())]
                yield pa.RecordBatch.from_arrays(cols, ["doc_id", "start", *(["n_tokens", "ids_crc32"] if digest_only else ["ids"])])

    return files.select("part", "seq", "docs", "nulls", "lengths", "payload").mapInArrow(decode, "doc_id long, start long, " + ("n_tokens long, ids_crc32 long" if digest_only else "ids binary"))


def new_path(spark) -> str:
    """A new place for a file set that lasts as long as the driver's process."""
    return session.new_path(spark, "ids")
