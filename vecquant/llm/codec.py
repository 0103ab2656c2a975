"""Byte-level BPE encoding and decoding of whole texts.

Encoding runs the tokenizers library over Arrow batches, with the ranks of a vocabulary file
turned into that library's form. Decoding looks every id up in the reversed byte table and
joins bytes, so that characters split over several tokens come back whole.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecquant.llm import bpe
from vecquant.llm.common import single_column, text_slices


def decode_ids(ids: np.ndarray, table: list[bytes]) -> bytes:
    """Bytes of the ids in order."""
    return b"".join(map(table.__getitem__, ids.tolist()))


def token_offsets(text: str, ids: np.ndarray, table: list[bytes]) -> list[tuple[int, int]]:
    """Characters (start, end) of every token; tokens inside one character share its place."""
    raw = text.encode()
    begins = np.cumsum(np.frombuffer(raw, dtype=np.uint8) & 0xC0 != 0x80) if raw else np.zeros(0, dtype=np.int64)
    out, at = [], 0
    for i in ids.tolist():
        end = at + len(table[i])
        out.append((int(begins[at]) - 1, int(begins[end - 1])) if end > at else (0, 0))
        at = end
    return out


def encode_documents(
    docs: DataFrame, ranks_path: str, id_column: str = "doc_id", text_column: str = "text", keep_ids: bool = False
) -> DataFrame:
    """Encode and decode every text.

    Rows: the id, n_tokens, ids_sha256 (of the ids as little-endian unsigned 32-bit integers),
    decoded_sha256 (of the decoded bytes), and with keep_ids the ids. A null text counts as
    empty (no tokens); repeated rows give repeated results; other columns are ignored. Texts of
    any length are encoded whole. ranks_path is read on the driver only.
    """
    definition = bpe.tokenizer_json(bpe.read_ranks(ranks_path))
    shipped, name = docs.sparkSession.sparkContext.broadcast(definition), bpe.digest(definition)
    kind = docs.schema[id_column].dataType.simpleString()
    fields = [pa.field("n_tokens", pa.int64()), pa.field("ids_sha256", pa.string()), pa.field("decoded_sha256", pa.string())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = bpe.per_worker("codec", name, lambda: bpe.PieceEncoder(shipped.value))
        table = bpe.per_worker("codec bytes", name, lambda: bpe.byte_table(shipped.value))
        for batch, texts in text_slices(batches, "text"):
            coded = encoder.encode(texts)
            counts = [len(x) // 4 for x in coded]
            decoded = [hashlib.sha256(decode_ids(np.frombuffer(x, dtype="<u4"), table)).hexdigest() for x in coded]
            columns = [single_column(batch, "id"), pa.array(counts, pa.int64())]
            columns += [pa.array([hashlib.sha256(x).hexdigest() for x in coded]), pa.array(decoded)]
            names = ["id", *(f.name for f in fields)]
            if keep_ids:
                columns.append(pa.array([np.frombuffer(x, dtype="<u4").astype(np.int32) for x in coded], pa.list_(pa.int32())))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(columns, names=names)

    schema = f"id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * keep_ids
    rows = docs.select(F.col(id_column).alias("id"), F.col(text_column).alias("text")).mapInArrow(run, schema)
    return rows.withColumnRenamed("id", id_column)


def decode_documents(coded: DataFrame, ranks_path: str, id_column: str = "doc_id", ids_column: str = "ids") -> DataFrame:
    """Text of every row's ids; bytes that are no UTF-8 (a cut character) become U+FFFD."""
    definition = bpe.tokenizer_json(bpe.read_ranks(ranks_path))
    shipped, name = coded.sparkSession.sparkContext.broadcast(definition), bpe.digest(definition)
    kind = coded.schema[id_column].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = bpe.per_worker("codec bytes", name, lambda: bpe.byte_table(shipped.value))
        for batch in batches:
            rows = single_column(batch, "ids").to_pylist()
            texts = [b"".join(table[i] for i in row or []).decode("utf-8", "replace") for row in rows]
            yield pa.RecordBatch.from_arrays([single_column(batch, "id"), pa.array(texts, pa.string())], names=["id", "text"])

    rows = coded.select(F.col(id_column).alias("id"), F.col(ids_column).alias("ids"))
    return rows.mapInArrow(run, f"id {kind}, text string").withColumnRenamed("id", id_column)
