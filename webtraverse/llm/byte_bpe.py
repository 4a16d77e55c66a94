"""Byte-level BPE over rank files, as a monoid: halves are encoded apart and joined by repairing the seam.

An element of the monoid is the token list of a byte string; ``join`` combines the lists of two neighbours. Around the
seam a window of tokens is encoded again from its bytes, and the window grows until the token pair at each of its rims
is *stable*: encoding the bytes of the pair alone gives the same two tokens. For rank-based BPE a token list is the
encoding of its bytes exactly if all of its neighbouring pairs are stable, so a window with stable rims proves that
every token outside it stays as it is. Decoding is the plain concatenation up the tree.

Behaviour at the edges: null text is empty text; empty text has no tokens and the hashes of empty strings; equal rows give
equal results; ids of documents may repeat or be null; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import TwoAgeCache, map_arrow, text_column

DEFAULT_RANKS = "byte_bpe_multi_50k.tiktoken"
LEAF_BYTES = 24
CACHE_ENTRIES = 500_000
ENCODED = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class ByteBpe:
    """Encoder and decoder for one rank table."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.table = [b""] * (max(ranks.values(), default=-1) + 1)
        for token, i in ranks.items():
            self.table[i] = token
        self._stable: dict[tuple[int, int], bool] = {}

    def leaf(self, data: bytes) -> list[int]:
        """Merge the pair of lowest rank, leftmost first, until none is left."""
        whole = self.ranks.get(data)
        if whole is not None:
            return [whole]
        ranks, parts = self.ranks, [data[i : i + 1] for i in range(len(data))]
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                r = ranks.get(parts[i] + parts[i + 1])
                if r is not None and (best is None or r < best):
                    best, at = r, i
            if best is None:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return [ranks[p] for p in parts]

    def stable(self, a: int, b: int) -> bool:
        pair = (a, b)
        known = self._stable.get(pair)
        if known is None:
            if len(self._stable) > 400_000:
                self._stable.clear()
            known = self._stable[pair] = self.leaf(self.table[a] + self.table[b]) == [a, b]
        return known

    def join(self, left: list[int], right: list[int]) -> list[int]:
        """The encoding of two neighbouring byte strings from their encodings."""
        if not left or not right:
            return left or right
        if self.stable(left[-1], right[0]):
            return left + right
        back, ahead = 1, 1
        while True:
            i, j = max(len(left) - back, 0), min(ahead, len(right))
            middle = self.leaf(b"".join(map(self.table.__getitem__, left[i:] + right[:j])))
            fits_left = i == 0 or self.stable(left[i - 1], middle[0])
            fits_right = j == len(right) or self.stable(middle[-1], right[j])
            if fits_left and fits_right:
                return left[:i] + middle + right[j:]
            back += 0 if fits_left else back
            ahead += 0 if fits_right else ahead

    def encode(self, data: bytes) -> list[int]:
        """Tree reduction: a bottom-up pass over leaves of a few bytes, joining neighbours level by level."""
        if len(data) <= LEAF_BYTES:
            return self.leaf(data) if data else []
        level = [self.leaf(data[i : i + LEAF_BYTES]) for i in range(0, len(data), LEAF_BYTES)]
        while len(level) > 1:
            level = [self.join(level[i], level[i + 1]) if i + 1 < len(level) else level[i] for i in range(0, len(level), 2)]
        return level[0]

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.table.__getitem__, ids))


class TextEncoder:
    """Whole texts: matches of the splitting pattern are encoded one by one, and their id strings joined."""

    def __init__(self, ranks_path: str | None = None, pattern: str | None = None):
        import public_tokenizers
        import regex

        self.bpe = ByteBpe(read_ranks(ranks_path or public_tokenizers.path(DEFAULT_RANKS)))
        self.split = regex.compile(pattern or public_tokenizers.PATTERN).findall
        self.cache = TwoAgeCache(CACHE_ENTRIES)

    def id_bytes(self, text: str) -> bytes:
        """The ids as little-endian unsigned 32-bit integers."""
        matches = self.split(text)
        for m in self.cache.missing(set(matches)):
            self.cache.now[m] = np.array(self.bpe.encode(m.encode()), dtype="<u4").tobytes()
        return b"".join(map(self.cache.now.__getitem__, matches))

    def decode_bytes(self, ids: bytes) -> bytes:
        return self.bpe.decode(np.frombuffer(ids, dtype="<u4").tolist())


_encoders: dict = {}


def _encoder(ranks_path, pattern) -> TextEncoder:
    key = (ranks_path, pattern)
    if key not in _encoders:
        _encoders[key] = TextEncoder(ranks_path, pattern)
    return _encoders[key]


def encode_documents(docs: DataFrame, ranks_path: str | None = None, pattern: str | None = None) -> DataFrame:
    """(doc_id, token_ids array<int>): the ids of each whole text."""

    def work(batches):
        enc = _encoder(ranks_path, pattern)
        for batch in batches:
            ids = [np.frombuffer(enc.id_bytes(t), dtype="<u4").astype("int32") for t in batch.column(1).to_pylist()]
            yield pa.record_batch([batch.column(0), pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "token_ids"])

    return map_arrow(docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_column(docs).alias("text")), work, "doc_id long, token_ids array<int>")


def decode_documents(encoded: DataFrame, ranks_path: str | None = None) -> DataFrame:
    """(doc_id, data binary): the bytes that the ids of each row stand for."""

    def work(batches):
        enc = _encoder(ranks_path, None)
        for batch in batches:
            data = [enc.bpe.decode(x or []) for x in batch.column(1).to_pylist()]
            yield pa.record_batch([batch.column(0), pa.array(data, pa.binary())], ["doc_id", "data"])

    return map_arrow(encoded.select("doc_id", "token_ids"), work, "doc_id long, data binary")


def round_trip_digest(docs: DataFrame, ranks_path: str | None = None, pattern: str | None = None) -> DataFrame:
    """Encode each whole text, decode its ids, and return the digests of both; one map over the rows, no shuffle."""

    def work(batches):
        enc = _encoder(ranks_path, pattern)
        for batch in batches:
            n, a, b = [], [], []
            for text in batch.column(1):
                ids = enc.id_bytes(text.as_py())
                n.append(len(ids) // 4)
                a.append(hashlib.sha256(ids).hexdigest())
                b.append(hashlib.sha256(enc.decode_bytes(ids)).hexdigest())
            yield pa.record_batch([batch.column(0), pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return map_arrow(docs.select(docs["doc_id"].cast("long").alias("doc_id"), text_column(docs).alias("text")), work, ENCODED)
