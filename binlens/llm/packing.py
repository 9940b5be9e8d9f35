"""Power-of-two decomposition packing: each document's ids are cut into pieces of lengths 2^k.

A document of n ids gives floor(n / size) full pieces and one piece for each set bit of the rest, longest first.
Pieces of one length form a bucket, every piece is a sequence of its own, so no sequence crosses documents and
none is padded.  A trainer draws batches from one bucket at a time.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binlens.llm.common import narrow
from binlens.llm.tokens import encoder

SIZE = 2048
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, bucket int"


def piece_lengths(n: int, size: int = SIZE) -> list[int]:
    """``size`` must be a power of two; 0 ids give no piece."""
    if size & (size - 1) or size < 1:
        raise ValueError("size must be a power of two")
    rest = n % size
    return [size] * (n // size) + [1 << k for k in range(size.bit_length() - 1, -1, -1) if rest >> k & 1]


def pack(docs: DataFrame, tokenizer: str, end_id: int = 1, size: int = SIZE, with_ids: bool = False) -> DataFrame:
    """One row for each piece: PIECES, sequence_id, offset (0), and the ids themselves if asked for.

    Null texts are empty: one piece of the end id.  Repeated rows are packed each for itself, with sequence ids of
    their own.  Only doc_id and text are read; an empty table gives no pieces.
    """
    schema = PIECES + (", ids array<int>" if with_ids else "")

    def run(batches):
        coder = encoder(tokenizer)
        for batch in batches:
            for a, flat, bounds in coder.encode(batch.column(1), end_id):
                ids = batch.column(0)[a : a + len(bounds) - 1].to_pylist()
                doc, start, length, crc, total, bucket, body = [], [], [], [], [], [], []
                for k, d in enumerate(ids):
                    lo, n = int(bounds[k]), int(bounds[k + 1] - bounds[k])
                    raw = memoryview(flat[lo : lo + n]).cast("B")
                    at = 0
                    for piece in piece_lengths(n, size):
                        doc.append(d)
                        start.append(at)
                        length.append(piece)
                        crc.append(zlib.crc32(raw[4 * at : 4 * (at + piece)]))
                        total.append(n)
                        bucket.append(piece.bit_length() - 1)
                        if with_ids:
                            body.append(flat[lo + at : lo + at + piece].astype(np.int32))
                        at += piece
                columns = [pa.array(doc, pa.int64()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64()),
                    pa.array(total, pa.int64()), pa.array(bucket, pa.int32())]
                names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "bucket"]
                if with_ids:
                    columns.append(pa.array(body, pa.list_(pa.int32())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names)

    pieces = narrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), run, schema)
    return pieces.withColumn("sequence_id", F.monotonically_increasing_id()).withColumn("offset", F.lit(0).cast("long"))


def buckets(pieces: DataFrame) -> DataFrame:
    """Sequences and ids of each bucket, for planning batches."""
    return pieces.groupBy("bucket").agg(F.count("*").alias("n_sequences"), F.sum("length").alias("n_ids"))
