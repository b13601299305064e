"""Token counts: Arrow functions that return lengths only.

A text is encoded by the byte-level BPE in the file given by name (``public_tokenizers.path``). Two engines
give the same ids: ``tokenizers`` (the library of the .json file) and a rank-merge engine (``tiktoken``)
over the same vocabulary, about four times as fast. The second one serves texts whose code points are all
below ``SAFE_LIMIT``, where the two libraries' Unicode tables agree; any other text goes to the first.

Batches are cut by bytes, not rows, so that a worker's memory is bounded by ``batch_bytes`` whatever the
lengths of the texts; a text longer than ``piece_chars`` is encoded in pieces cut before a blank that
follows a visible character: no token spans such a place, so lengths add up exactly.

Defined results: null text counts as the empty text (0 tokens, 0 bytes); an empty table gives an empty
table; repeated rows are counted each; other columns of the input are carried along unless they clash with
an output name, in which case the output's value replaces them.
"""

from __future__ import annotations

import base64
import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

SPECIAL = "<|endoftext|>"
SPECIAL_ID = 50256
#: Code points below this (Latin, Greek, Cyrillic, Armenian) were settled long before either library's Unicode version.
SAFE_LIMIT = 0x530
PIECE_CHARS = 1 << 20
BATCH_BYTES = 8 << 20


@functools.cache
def library(name: str = "byte_bpe_50k.json"):
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    import public_tokenizers
    from tokenizers import Tokenizer

    return Tokenizer.from_file(public_tokenizers.path(name))


@functools.cache
def ranks(name: str = "byte_bpe_50k.tiktoken"):
    import public_tokenizers
    import tiktoken

    with open(public_tokenizers.path(name), "rb") as f:
        table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("byte_bpe", pat_str=public_tokenizers.PATTERN, mergeable_ranks=table, special_tokens={SPECIAL: SPECIAL_ID})


def safe_pieces(text: str, size: int = PIECE_CHARS) -> Iterator[str]:
    """Cut ``text`` before blanks that follow a visible character, at the first such place from ``size`` on."""
    at = 0
    while len(text) - at > size:
        cut = text.find(" ", at + size)
        while cut > 0 and text[cut - 1].isspace():
            cut = text.find(" ", cut + 1)
        if cut < 0:
            break
        yield text[at:cut]
        at = cut
    yield text[at:] if at else text


def encode(text: str | None, engine: str = "ranks") -> np.ndarray:
    """Ids of one text as an unsigned 32-bit array; the special string inside a text is the special token."""
    if not text:
        return np.empty(0, np.uint32)
    parts = []
    for piece in safe_pieces(text):
        if engine == "ranks" and (piece.isascii() or max(piece) < chr(SAFE_LIMIT)):
            if SPECIAL in piece:
                ids = ranks().encode(piece, allowed_special={SPECIAL})
                parts.append(np.asarray(ids, np.uint32))
            else:
                parts.append(np.asarray(ranks().encode_ordinary(piece), np.uint32))
        else:
            parts.append(np.asarray(library().encode(piece, add_special_tokens=False).ids, np.uint32))
    return parts[0] if len(parts) == 1 else np.concatenate(parts)


def by_bytes(batches: Iterator[pa.RecordBatch], column: str, limit: int = BATCH_BYTES) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about ``limit`` bytes of ``column`` at most (one row at least)."""
    for b in batches:
        if not b.num_rows:
            continue
        text = b.column(b.schema.get_field_index(column))
        sizes = np.asarray(pc.fill_null(pc.binary_length(text), 0)).astype(np.int64)
        part = (np.cumsum(sizes) - sizes) // limit
        edges = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), b.num_rows]
        for s, e in zip(edges, edges[1:], strict=False):
            yield b.slice(s, e - s)


def token_counts(docs: DataFrame, text: str = "text", over: int = 512, engine: str = "ranks", batch_bytes: int = BATCH_BYTES) -> DataFrame:
    """Every row of ``docs`` without its text, plus n_bytes, n_tokens and over_limit (more tokens than ``over``)."""
    made = ("n_bytes", "n_tokens", "over_limit")
    keep = [c for c in docs.columns if c not in (*made, text)]
    narrow = docs.select(*keep, text)
    out = T.StructType([*(f for f in narrow.schema.fields if f.name != text), T.StructField("n_bytes", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("over_limit", T.BooleanType())])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in by_bytes(batches, text, batch_bytes):
            i = b.schema.get_field_index(text)
            n_bytes = pc.fill_null(pc.binary_length(b.column(i)), 0).cast(pa.int64())
            n = np.fromiter((len(encode(v.as_py(), engine)) for v in b.column(i)), np.int64, b.num_rows)
            columns = [b.column(k) for k in range(b.num_columns) if k != i]
            yield pa.RecordBatch.from_arrays([*columns, n_bytes, pa.array(n), pa.array(n > over)], [*keep, *made])

    return narrow.mapInArrow(count, out)


def op5_token_counts(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return token_counts(docs).select("doc_id", "n_bytes", "n_tokens", "over_limit")
