"""Byte-level BPE encoding and decoding by a local rank file, through the tiktoken library.

The library's regular expression recurses on long runs, so a text that is long or holds a long run of white space is
first cut where no match can reach across:

* between a word character and a following space or line feed: no alternative has white space after anything else;
* what is still long after that, or holds a long white-space run, is matched by the ``regex`` module, and each match is
  encoded as a single piece.

Encoded documents are packed as little-endian unsigned 32-bit ids, the usual token shard format. Decoding returns raw
bytes, so ids that end inside a character survive.

Defined results: a null text encodes as the empty text (no ids); an empty table gives an empty table; texts of any
length are encoded whole; null ids decode to empty bytes; repeated rows encode alike; extra columns are carried along, but
columns that have the names of the results (``token_ids``, ``decoded``) are replaced.
"""

from __future__ import annotations

import base64
import functools
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from augspark.llm.text import small_batches

RANK_FILE = "byte_bpe_multi_50k.tiktoken"
#: Texts above this many characters, and white-space runs above RUN, are cut first.
LONG = 20_000
RUN = 200
_SPACES = re.compile(r"\s{%d,}" % RUN)
_EDGE = re.compile(r"(?<=[0-9A-Za-z])(?=[ \n])")


def rank_path(name: str = RANK_FILE) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@functools.lru_cache(4)
def encoding(path: str):
    """The tokenizer of a rank file, once a process."""
    import public_tokenizers
    import tiktoken

    with open(path, "rb") as lines:
        ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}
    return tiktoken.Encoding("local", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


@functools.lru_cache(1)
def _pattern():
    import public_tokenizers
    import regex

    return regex.compile(public_tokenizers.PATTERN)


def safe_chunks(text: str, size: int = LONG) -> Iterator[str]:
    """Cut a text at safe boundaries into pieces of about ``size`` characters; a piece without boundary stays whole."""
    at = 0
    while len(text) - at > size:
        edge = _EDGE.search(text, at + size)
        if not edge:
            break
        yield text[at : edge.start()]
        at = edge.start()
    yield text[at:]


def encode_text(enc, text: str) -> list[int]:
    """The ids of a whole text, as the library would give them for each match of its pattern."""
    if len(text) <= LONG and not _SPACES.search(text):
        return enc.encode_ordinary(text)
    ids: list[int] = []
    for chunk in safe_chunks(text):
        if len(chunk) <= 2 * LONG and not _SPACES.search(chunk):
            ids += enc.encode_ordinary(chunk)
        else:
            for match in _pattern().finditer(chunk):
                ids += enc._encode_single_piece(match[0])
    return ids


def pack(ids) -> bytes:
    return np.asarray(ids, dtype="<u4").tobytes()


def unpack(packed: bytes) -> list[int]:
    return np.frombuffer(packed, dtype="<u4").tolist()


def encoder(path: str):
    """A vectorised function: text -> packed ids."""

    @F.pandas_udf("binary")
    def encode(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        enc = encoding(path)
        for batch in texts:
            yield pd.Series([pack(encode_text(enc, t or "")) for t in batch], dtype=object)

    return encode


def decoder(path: str):
    """A vectorised function: packed ids -> raw bytes."""

    @F.pandas_udf("binary")
    def decode(packed: Iterator[pd.Series]) -> Iterator[pd.Series]:
        enc = encoding(path)
        for batch in packed:
            yield pd.Series([enc.decode_bytes(unpack(p or b"")) for p in batch], dtype=object)

    return decode


def count_ids(packed: Column) -> Column:
    return (F.octet_length(packed) / 4).cast("long")


def encode(docs: DataFrame, path: str | None = None, text: str = "text", out: str = "token_ids") -> DataFrame:
    """docs with the packed ids of each whole text in ``out``."""
    small_batches(docs.sparkSession)
    return docs.withColumn(out, encoder(path or rank_path())(F.col(text)))


def decode(tokens: DataFrame, path: str | None = None, ids: str = "token_ids", out: str = "decoded") -> DataFrame:
    """tokens with the raw bytes that its ids stand for in ``out``."""
    small_batches(tokens.sparkSession)
    return tokens.withColumn(out, decoder(path or rank_path())(F.col(ids)))
