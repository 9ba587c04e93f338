"""Encoding and decoding of whole tables by the streaming byte-pair transducer.

Defined results: null or empty text has no tokens; special strings in a text become their ids, as
the library does it; equal rows give equal results; further columns are ignored; an empty table
gives an empty table.
"""

from __future__ import annotations

from hashlib import sha256

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift.llm.bpe import ByteStreamDecoder, byte_encoder, text_blocks
from gradsift.llm.common import table
from gradsift.llm.packing import tokenizer_path


class Digest:
    """What is kept of a text while its tokens pass: their number, two digests, the decoder's state."""

    def __init__(self, decoder: ByteStreamDecoder, keep: bool):
        self.n, self.ids, self.text, self.machine = 0, sha256(), sha256(), decoder.fresh()
        self.kept: tuple[list, list] | None = ([], []) if keep else None

    def take(self, got: bytes, raw: bytes) -> None:
        """More ids, and the bytes they stand for."""
        self.n += len(got) // 4
        self.ids.update(got)
        self._text(self.machine.decode(raw))
        if self.kept:
            self.kept[0].append(np.frombuffer(got, "<u4"))

    def _text(self, text: str) -> None:
        self.text.update(text.encode())
        if self.kept:
            self.kept[1].append(text)

    def close(self) -> tuple:
        self._text(self.machine.decode(b"", True))
        out = (self.n, self.ids.hexdigest(), self.text.hexdigest())
        return (*out, np.concatenate([np.zeros(0, "<u4"), *self.kept[0]]), "".join(self.kept[1])) if self.kept else out


def encode_decode(docs: DataFrame, path: str, with_output: bool = False) -> DataFrame:
    """Per document the number of tokens and digests of ids and decoded text (or both themselves).

    Every text passes through its stream in blocks; only digests and the open ends are held.
    """
    kinds = [pa.int64(), pa.string(), pa.string(), *([pa.list_(pa.int64()), pa.string()] if with_output else [])]

    def run(batches):
        encoder, decoder = byte_encoder(path), ByteStreamDecoder(path)
        for batch in batches:
            texts, rows = [t or "" for t in batch.column(1).to_pylist()], []
            for i, j in text_blocks(texts):
                own = [Digest(decoder, with_output) for _ in range(i, j)]
                for k, got in encoder.rounds(texts[i:j]):
                    own[k].take(got, decoder.raw(np.frombuffer(got, "<u4")))
                rows += [d.close() for d in own]
            cols = zip(*rows, strict=True) if rows else ([] for _ in kinds)
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "ids", "decoded"]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(list(c), t) for c, t in zip(cols, kinds, strict=True))], names[: 1 + len(kinds)])

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(run, schema + (", ids array<long>, decoded string" if with_output else ""))


def op3_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents through the byte-level vocabulary and back."""
    return encode_decode(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"))
