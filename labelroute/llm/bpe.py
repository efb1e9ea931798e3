"""Byte-level BPE encoding and decoding with the tiktoken library.

The rank file is a local path (a parameter), loaded once per Python worker.
Whole texts are encoded: a long text is split beforehand at boundaries that no
match of the pre-splitting pattern can cross, so the ids equal those of one
call over the whole text and memory stays bounded by a chunk.

Defined results: null text encodes as the empty text (no ids, empty bytes);
rows are handled one by one, so ties, repeated rows and extra columns change
nothing; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import public_tokenizers
import pyarrow as pa
import regex
import tiktoken
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

RANKS = public_tokenizers.path("byte_bpe_50k.tiktoken")
#: Texts above this many code points are split before encoding.
CHUNK = 1 << 16
#: A piece without any safe boundary longer than this is split by the pattern
#: itself and each match is encoded alone.
GIANT = 1 << 19
#: Between a non-space and a space that a non-space follows: a match holds
#: white space only at its first place or throughout, so none crosses here.
_SAFE = regex.compile(r"(?<=\S)(?= \S)")

_encoders: dict[tuple[str, str], tiktoken.Encoding] = {}


def encoder(ranks_path: str = RANKS, pattern: str = public_tokenizers.PATTERN) -> tiktoken.Encoding:
    key = (ranks_path, pattern)
    if key not in _encoders:
        with open(ranks_path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        _encoders[key] = tiktoken.Encoding(
            "local", pat_str=pattern, mergeable_ranks=ranks, special_tokens={}
        )
    return _encoders[key]


def pieces(text: str, chunk: int = CHUNK) -> Iterator[str]:
    """Split at safe boundaries; every piece but those without one is about ``chunk`` long."""
    start = 0
    while len(text) - start > chunk:
        m = _SAFE.search(text, start + chunk)
        if m is None:
            break
        yield text[start : m.start()]
        start = m.start()
    yield text[start:]


def encode(text: str, enc: tiktoken.Encoding, chunk: int = CHUNK, giant: int = GIANT) -> list[int]:
    if len(text) <= chunk:
        return enc.encode_ordinary(text)
    out: list[int] = []
    split = None
    for piece in pieces(text, chunk):
        if len(piece) <= giant:
            out += enc.encode_ordinary(piece)
        else:
            split = split or regex.compile(enc._pat_str)
            for m in split.finditer(piece):
                out += enc._encode_single_piece(m[0])
    return out


def encode_column(
    df: DataFrame, text: str = "text", ids: str = "ids", ranks_path: str = RANKS
) -> DataFrame:
    """Add ``ids`` (array of int) to every row of ``df``; other columns pass through."""
    from .columns import mapped  # loads pandas, which workers of the other functions do without

    common.tune_arrow(df.sparkSession)
    return df.withColumn(ids, mapped(lambda t: encode(t or "", encoder(ranks_path)), "array<int>")(F.col(text)))


def decode_column(df: DataFrame, ids: str = "ids", raw: str = "raw", ranks_path: str = RANKS) -> DataFrame:
    """Add the raw bytes that ``ids`` stand for; null ids give empty bytes."""
    from .columns import mapped

    back = lambda t: b"" if t is None else encoder(ranks_path).decode_bytes([int(x) for x in t])
    return df.withColumn(raw, mapped(back, "binary")(F.col(ids)))


def encode_documents(df: DataFrame, ranks_path: str = RANKS) -> DataFrame:
    """``df`` with ids, n_tokens and whether decoding gives the text's bytes back.

    A column of ``df`` with one of these names is replaced."""
    common.tune_arrow(df.sparkSession)
    df = df.drop("ids", "n_tokens", "round_trip")
    at = df.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(ranks_path)
        for b in batches:
            ids, same = [], []
            for t in b.column(at).to_pylist():
                ids.append(encode(t or "", enc))
                same.append(enc.decode_bytes(ids[-1]) == (t or "").encode())
            yield pa.RecordBatch.from_arrays(
                [*b.columns, pa.array(ids, pa.list_(pa.int32())), pa.array([len(x) for x in ids], pa.int64()), pa.array(same)],
                [*b.schema.names, "ids", "n_tokens", "round_trip"],
            )

    schema = T.StructType(
        [*df.schema.fields, T.StructField("ids", T.ArrayType(T.IntegerType())), T.StructField("n_tokens", T.LongType()), T.StructField("round_trip", T.BooleanType())]
    )
    return df.mapInArrow(run, schema)


def round_trip(df: DataFrame, ranks_path: str = RANKS) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every whole text."""
    common.tune_arrow(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(ranks_path)
        for b in batches:
            n, a, d = [], [], []
            for t in b.column(1).to_pylist():
                ids = encode(t or "", enc)
                n.append(len(ids))
                a.append(hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest())
                d.append(hashlib.sha256(enc.decode_bytes(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(d, pa.string())],
                ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    return df.select(F.col("doc_id").cast("long"), "text").mapInArrow(
        run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
    )
