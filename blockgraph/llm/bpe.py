"""Byte-level BPE encoding and decoding with the tiktoken library.

A local rank file gives the vocabulary. tiktoken's own regex engine walks a
text in one go, so texts longer than ``piece_chars`` are first cut where no
match of the pattern can cross: in front of white space that follows another
character class, and between a letter and a digit. Each part is encoded by
itself and the ids are concatenated, which gives the ids of the whole text.

Edge cases: a null or empty text has no ids and decodes to no bytes; repeated
rows are encoded each; extra columns are ignored by ``encode`` unless named in
``keep``; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import as_text, portions

#: Places at which a long text may be cut: before white space after anything
#: else, or between a letter and a digit (either order).
_SAFE = regex.compile(r"(?<=\S)(?=\s)|(?<=\p{L})(?=\p{N})|(?<=\p{N})(?=\p{L})")
_loaded: dict[tuple[str, str], object] = {}


def tokenizer(rank_file: str, pattern: str):
    """The encoder of a rank file; loaded once in each Python worker."""
    key = (rank_file, pattern)
    if key not in _loaded:
        import tiktoken

        ranks = {}
        with open(rank_file, "rb") as f:
            for line in f:
                if line.strip():
                    token, rank = line.split()
                    ranks[base64.b64decode(token)] = int(rank)
        _loaded[key] = tiktoken.Encoding("local", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
    return _loaded[key]


def pieces(text: str, piece_chars: int) -> Iterator[str]:
    """Cut a text at safe boundaries into parts of about piece_chars; a stretch
    without a safe boundary stays whole."""
    start = 0
    while len(text) - start > piece_chars:
        m = _SAFE.search(text, start + piece_chars)
        if m is None:
            break
        yield text[start : m.start()]
        start = m.start()
    yield text[start:]


def encode_text(enc, text: str, piece_chars: int = 65536) -> list[int]:
    if len(text) <= piece_chars:
        return enc.encode_ordinary(text)
    ids: list[int] = []
    for part in pieces(text, piece_chars):
        ids.extend(enc.encode_ordinary(part))
    return ids


def encode(df: DataFrame, rank_file: str, pattern: str, keep: tuple[str, ...] = ("doc_id",), text: str = "text", piece_chars: int = 65536) -> DataFrame:
    """The kept columns and ``ids array<int>``, one row for each row of df."""

    def run(batches):
        enc = tokenizer(rank_file, pattern)
        for b in portions(batches):
            ids = [encode_text(enc, t, piece_chars) if t else [] for t in b.column(len(keep)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keep)], pa.array(ids, pa.list_(pa.int32()))], names=[*keep, "ids"])

    src = df.select(*keep, text)
    schema = ", ".join([*(f"`{c}` {t}" for c, t in src.dtypes[: len(keep)]), "ids array<int>"])
    return src.mapInArrow(run, schema)


def decode(df: DataFrame, rank_file: str, pattern: str, keep: tuple[str, ...] = ("doc_id",), ids: str = "ids") -> DataFrame:
    """The kept columns and ``bytes binary``: the raw bytes of the ids."""

    def run(batches):
        enc = tokenizer(rank_file, pattern)
        for b in portions(batches):
            out = [enc.decode_bytes(x) if x else b"" for x in b.column(len(keep)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keep)], pa.array(out, pa.binary())], names=[*keep, "bytes"])

    src = df.select(*keep, ids)
    schema = ", ".join([*(f"`{c}` {t}" for c, t in src.dtypes[: len(keep)]), "bytes binary"])
    return src.mapInArrow(run, schema)


def digests(df: DataFrame, rank_file: str, pattern: str, keep: tuple[str, ...] = ("doc_id",), text: str = "text", piece_chars: int = 65536) -> DataFrame:
    """Encode and decode each text in one pass and return n_tokens,
    ids_sha256 and decoded_sha256; raises if a round trip loses bytes."""
    n = len(keep)

    def run(batches):
        enc = tokenizer(rank_file, pattern)
        for b in portions(batches):
            counts, of_ids, of_bytes = [], [], []
            for t in b.column(n).to_pylist():
                ids = encode_text(enc, t, piece_chars) if t else []
                back = enc.decode_bytes(ids)
                if back != as_text(t):
                    raise ValueError("decoding does not give back the encoded bytes")
                counts.append(len(ids))
                of_ids.append(hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest())
                of_bytes.append(hashlib.sha256(back).hexdigest())
            yield pa.RecordBatch.from_arrays(
                [*b.columns[:n], pa.array(counts, pa.int64()), pa.array(of_ids), pa.array(of_bytes)],
                names=[*keep, "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    src = df.select(*keep, text)
    schema = ", ".join([*(f"`{c}` {t}" for c, t in src.dtypes[:n]), "n_tokens long, ids_sha256 string, decoded_sha256 string"])
    return src.mapInArrow(run, schema)


def count(df: DataFrame, rank_file: str, pattern: str, keep: tuple[str, ...] = ("doc_id",), text: str = "text", piece_chars: int = 65536) -> DataFrame:
    """The kept columns, n_tokens and n_words (both long) of each text."""
    n = len(keep)

    def run(batches):
        enc = tokenizer(rank_file, pattern)
        for b in portions(batches):
            texts = b.column(n).to_pylist()
            tokens = [len(encode_text(enc, t, piece_chars)) if t else 0 for t in texts]
            words = [len(as_text(t).split()) for t in texts]
            yield pa.RecordBatch.from_arrays([*b.columns[:n], pa.array(tokens, pa.int64()), pa.array(words, pa.int64())], names=[*keep, "n_tokens", "n_words"])

    src = df.select(*keep, text)
    schema = ", ".join([*(f"`{c}` {t}" for c, t in src.dtypes[:n]), "n_tokens long, n_words long"])
    return src.mapInArrow(run, schema)
