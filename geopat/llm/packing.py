"""Packing by power-of-two decomposition.

Each document becomes one run of token ids (its ids, then a separator).  The run is cut
into pieces of the longest sequence length and, for the rest, of the powers of two of
its binary form, longest first.  A piece is a sequence of its own, filed in the bucket
of its length: a sequence never crosses documents, and since every length is a power of
two nothing is padded.

Nulls and empty texts give the separator alone: one piece of length 1.  Repeated rows
are packed once each.  An empty table gives no pieces.  Very long texts only give more
pieces.  Other columns are not read.  There is no shuffle: pieces are cut where the
text is read, and ids of sequences are the task's number and a running number.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ship, table

SEPARATOR = 0
LONGEST = 1024
VOCABULARY = "byte_bpe_50k.json"
_SPECIAL = "<|endoftext|>"
_encoders: dict[str, object] = {}


class Encoder:
    """Byte-level BPE ids of a `tokenizers` file.

    Where the same vocabulary lies beside it as ranks, ordinary texts go through the
    faster library; it gives the same ids (tested on random Unicode).  Texts with a special token's
    string go through the file itself.
    """

    def __init__(self, path: str):
        import os

        from tokenizers import Tokenizer

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        self.full = Tokenizer.from_file(path)
        self.fast = None
        ranks = path.removesuffix(".json") + ".tiktoken"
        if path.endswith("byte_bpe_50k.json") and os.path.exists(ranks):
            import public_tokenizers
            import tiktoken

            with open(ranks, "rb") as lines:
                table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
            self.fast = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=table, special_tokens={})

    def ids(self, text: str) -> list[int]:
        if self.fast is not None and _SPECIAL not in text:
            return self.fast.encode_ordinary(text)
        return self.full.encode(text, add_special_tokens=False).ids


def encoder(path: str) -> Encoder:
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def piece_lengths(n: int, longest: int = LONGEST) -> list[int]:
    """Lengths that sum to n: as many of the longest as fit, then the powers of two of the rest."""
    rest = n % longest
    return [longest] * (n // longest) + [1 << b for b in range(longest.bit_length() - 1, -1, -1) if rest >> b & 1]


_SCHEMA = "doc_id long, start long, length long, ids binary, doc_tokens long"


def pack(docs: DataFrame, vocabulary: str | None = None, longest: int = LONGEST) -> DataFrame:
    """One row per piece: doc_id, start, length, ids (little-endian unsigned 32-bit), doc_tokens, sequence_id, offset, bucket.

    `vocabulary` is the path of a `tokenizers` file on the executors; `longest` a power of two.
    """
    if longest < 1 or longest & (longest - 1):
        raise ValueError("longest must be a power of two")
    ship(docs.sparkSession)
    if vocabulary is None:
        import public_tokenizers

        vocabulary = public_tokenizers.path(VOCABULARY)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(vocabulary)
        for batch in batches:
            out: tuple[list, ...] = ([], [], [], [], [])
            held = 0
            for doc_id, text in zip(batch["doc_id"], batch["text"], strict=True):
                ids = np.array([*own.ids(text.as_py() or ""), SEPARATOR], dtype="<u4")
                start = 0
                for length in piece_lengths(len(ids), longest):
                    for column, value in zip(out, (doc_id.as_py(), start, length, ids[start : start + length].tobytes(), len(ids)), strict=True):
                        column.append(value)
                    start += length
                held += len(ids)
                if held > 1 << 20:
                    yield _pieces(out)
                    out, held = ([], [], [], [], []), 0
            if out[0]:
                yield _pieces(out)

    pieces = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text")).mapInArrow(cut, _SCHEMA)
    return pieces.withColumns({
        "sequence_id": F.monotonically_increasing_id(),
        "offset": F.lit(0).cast("long"),
        "bucket": F.log2("length").cast("int"),
    })


def _pieces(out: tuple[list, ...]) -> pa.RecordBatch:
    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int64())
    names = ("doc_id", "start", "length", "ids", "doc_tokens")
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds, strict=True)], names=list(names))


def digest(pieces: DataFrame) -> DataFrame:
    """The pieces with a checksum in place of their ids."""
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset", "bucket")


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(pack(table(spark, sf_dir, "documents")))
