"""Byte-level BPE encoding and decoding with a local rank file.

Long texts are cut at safe boundaries before the tokenizer sees them: every match of the splitting pattern that holds white
space begins with it, so no match runs across a place where a white-space character follows another kind of character. Pieces cut
there encode to the same ids as the whole text, and the look-ahead of the pattern sees the same next character. A run without any
white space stays one piece. A very long run of white space is one match of the pattern (all of it at the end of a text, else all but
its last character, which belongs to what follows); it is merged as that match, and the pattern's matcher, which recurses on such runs, never sees it.

Null text counts as empty: no ids, no bytes. The ids of repeated rows are repeated; other columns are never read. An empty table
gives an empty result.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from elastipool.llm.common import lean, prepare, table

#: Characters of a piece handed to the tokenizer at once, as long as a safe boundary follows.
PIECE = 1 << 16
RANKS = "byte_bpe_50k.tiktoken"
SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
_BOUNDARY = re.compile(r"(?<=\S)(?=[ \t\n\r])")
#: White space as the pattern's matcher knows it, in runs too long for that matcher.
_LONG_RUN = re.compile("[\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]{4096,}")
_CODERS: dict[str, Coder] = {}


def read_ranks(path: str) -> bytes:
    with open(path, "rb") as f:
        return f.read()


class Coder:
    """Encoder and decoder of one rank file (its bytes are sent with the job: about 1 MB, whatever the corpus)."""

    def __init__(self, ranks: bytes, pattern: str):
        import tiktoken

        table_ = {base64.b64decode(a): int(b) for a, b in map(bytes.split, ranks.splitlines()) if a}
        self.enc = tiktoken.Encoding("local", pat_str=pattern, mergeable_ranks=table_, special_tokens={})
        self.bytes_of = [b""] * (max(table_.values()) + 1)
        for piece, i in table_.items():
            self.bytes_of[i] = piece

    @staticmethod
    def cached(ranks: bytes, pattern: str) -> Coder:
        key = hashlib.sha1(ranks + pattern.encode()).hexdigest()
        if key not in _CODERS:
            _CODERS[key] = Coder(ranks, pattern)
        return _CODERS[key]

    def pieces(self, text: str, size: int = PIECE) -> Iterator[str]:
        start = 0
        while len(text) - start > size:
            cut = _BOUNDARY.search(text, start + size)
            if not cut:
                break
            yield text[start : cut.start()]
            start = cut.start()
        yield text[start:] if start else text

    def encode(self, text: str, size: int = PIECE) -> np.ndarray:
        ids, at = [], 0
        for run in _LONG_RUN.finditer(text) if len(text) >= 4096 else ():
            end = run.end() - (run.end() < len(text))
            ids += [np.asarray(self.enc.encode_ordinary(p), np.uint32) for p in self.pieces(text[at : run.start()], size)]
            ids.append(np.asarray(self.enc._core_bpe.encode_single_piece(text[run.start() : end].encode()), np.uint32))
            at = end
        ids += [np.asarray(self.enc.encode_ordinary(p), np.uint32) for p in self.pieces(text[at:], size)]
        return ids[0] if len(ids) == 1 else np.concatenate(ids)

    def decode(self, ids: np.ndarray) -> bytes:
        """Raw bytes of the ids, joined; ids need not end at character borders."""
        return b"".join(map(self.bytes_of.__getitem__, ids.tolist()))


def encoded(docs: DataFrame, ranks: bytes, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids) with the ids as array<int>."""
    prepare(docs.sparkSession)

    def run(batches):
        coder = Coder.cached(ranks, pattern)
        for b in batches:
            yield pa.RecordBatch.from_pydict({"doc_id": b.column(0), "ids": pa.array([coder.encode(t or "").astype(np.int32) for t in b.column(1).to_pylist()], pa.list_(pa.int32()))})

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].cast("string").alias("text")).mapInArrow(lean(run), "doc_id long, ids array<int>")


def digests(docs: DataFrame, ranks: bytes, pattern: str, id_col: str = "doc_id", text_col: str = "text", keep: str | None = None) -> DataFrame:
    """Ids of every whole text and the bytes they decode to, as counts and digests in one pass (ids are never shuffled)."""
    prepare(docs.sparkSession)

    def run(batches):
        coder = Coder.cached(ranks, pattern)
        for b in batches:
            n, si, sd = [], [], []
            for t in b.column(1).to_pylist():
                ids = coder.encode(t or "")
                n.append(len(ids))
                si.append(hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest())
                sd.append(hashlib.sha256(coder.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_pydict({"doc_id": b.column(0), "n_tokens": pa.array(n, pa.int64()), "ids_sha256": pa.array(si, pa.string()), "decoded_sha256": pa.array(sd, pa.string())})

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].cast("string").alias("text")).mapInArrow(lean(run), SCHEMA)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return digests(table(spark, sf_dir, "documents"), read_ranks(public_tokenizers.path(RANKS)), public_tokenizers.PATTERN)
