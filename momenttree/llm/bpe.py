"""Byte-level BPE encoding and decoding.

Encoding splits a text at added tokens, then into pre-token pieces, then merges each piece: the symbols
form a doubly linked list, candidate merges wait in a priority queue ordered by (rank, position), and an
entry whose pair has changed since it was queued is skipped when it surfaces.  Decoding concatenates the
byte strings of the vocabulary.

Defined results: a null text counts as empty; an empty text has no ids and decodes to ""; very long pieces
cost O(n log n); rows are independent, so repeated rows give repeated results; an empty table gives an empty
table; output columns are only those named here, so extra input columns cannot clash.
"""

from __future__ import annotations

import heapq
import json
import re
import struct
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from momenttree.llm.runtime import ship, text_batches

#: Fixed value: the published pre-token pattern of byte-level BPE vocabularies.
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Every Unicode version agrees on the classes of the code points below this one.
SETTLED = 0x500
CACHE_ENTRIES = 700_000
CACHED_PIECE = 48


def default_vocabulary() -> str:
    """Path of the public 50k byte-level vocabulary; operators take another path as a parameter."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def byte_alphabet() -> dict[str, int]:
    """Printable stand-in character -> byte: printable Latin-1 bytes stand for themselves, others follow from 256 on."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(rest)}


class PieceCache(dict):
    """Piece -> packed ids, bounded; very long pieces are never kept."""

    def __init__(self, merge):
        super().__init__()
        self.merge = merge

    def __missing__(self, piece: str) -> bytes:
        ids = self.merge(piece.encode("utf-8"))
        packed = struct.pack(f"<{len(ids)}I", *ids)
        if len(piece) <= CACHED_PIECE:
            if len(self) >= CACHE_ENTRIES:
                self.clear()
            self[piece] = packed
        return packed


class ByteBpe:
    """One vocabulary with its merge ranks."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        stand_in = byte_alphabet()
        vocab = spec["model"]["vocab"]
        self.bytes_of = {i: bytes(stand_in[c] for c in token) for token, i in vocab.items()}
        self.of_byte = [vocab[c] for c, _ in sorted(stand_in.items(), key=lambda x: x[1])]
        self.joins: dict[int, int] = {}
        for rank, pair in enumerate(spec["model"]["merges"]):
            left, right = pair.split(" ") if isinstance(pair, str) else pair
            self.joins[vocab[left] << 20 | vocab[right]] = rank << 20 | vocab[left + right]
        self.added = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        for content, i in self.added.items():
            self.bytes_of[i] = content.encode("utf-8")
        self.at_added = re.compile("(" + "|".join(map(re.escape, sorted(self.added, key=len, reverse=True))) + ")") if self.added else None
        self.pieces = regex.compile(PIECES).findall
        self.unsettled = re.compile(f"[{chr(SETTLED)}-{chr(0x10FFFF)}]").search
        self.packed = PieceCache(self.merge)
        self._library = None

    def merge(self, piece: bytes) -> list[int]:
        symbols = [self.of_byte[b] for b in piece]
        n = len(symbols)
        if n < 2:
            return symbols
        joins = self.joins
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        queue = []
        for i in range(n - 1):
            found = joins.get(symbols[i] << 20 | symbols[i + 1])
            if found is not None:
                queue.append((found >> 20) << 40 | i)
        heapq.heapify(queue)
        while queue:
            entry = heapq.heappop(queue)
            i = entry & 0xFFFFFFFFFF
            j = after[i]
            if symbols[i] < 0 or j >= n:
                continue
            found = joins.get(symbols[i] << 20 | symbols[j])
            if found is None or found >> 20 != entry >> 40:
                continue  # stale: one side was merged after this was queued
            symbols[i], symbols[j] = found & 0xFFFFF, -1
            k = after[i] = after[j]
            if k < n:
                before[k] = i
                found = joins.get(symbols[i] << 20 | symbols[k])
                if found is not None:
                    heapq.heappush(queue, (found >> 20) << 40 | i)
            h = before[i]
            if h >= 0:
                found = joins.get(symbols[h] << 20 | symbols[i])
                if found is not None:
                    heapq.heappush(queue, (found >> 20) << 40 | h)
        return [s for s in symbols if s >= 0]

    def split(self, text: str) -> list[str]:
        """Pre-token pieces.  Texts with code points on which Unicode versions differ are split by the tokenizers library."""
        if self.unsettled(text) is None:
            return self.pieces(text)
        if self._library is None:
            from tokenizers.pre_tokenizers import ByteLevel

            self._library = ByteLevel(add_prefix_space=False, use_regex=True)
        return [text[a:b] for _, (a, b) in self._library.pre_tokenize_str(text)]

    def encode_packed(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        get = self.packed.__getitem__
        if self.at_added is None or not any(a in text for a in self.added):
            return b"".join(map(get, self.split(text)))
        parts = []
        for part in self.at_added.split(text):
            if part in self.added:
                parts.append(struct.pack("<I", self.added[part]))
            elif part:
                parts += map(get, self.split(part))
        return b"".join(parts)

    def encode(self, text: str) -> list[int]:
        packed = self.encode_packed(text)
        return list(struct.unpack(f"<{len(packed) // 4}I", packed))

    def decode_packed(self, packed: bytes) -> str:
        ids = struct.unpack(f"<{len(packed) // 4}I", packed)
        return b"".join(map(self.bytes_of.__getitem__, ids)).decode("utf-8", "replace")

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.bytes_of.__getitem__, ids)).decode("utf-8", "replace")


_LOADED: dict[str, ByteBpe] = {}


def load(path: str) -> ByteBpe:
    """One copy of a vocabulary for each Python worker."""
    if path not in _LOADED:
        _LOADED[path] = ByteBpe(path)
    return _LOADED[path]


def _rows(path: str, decode: bool, packed: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        kind = pa.binary() if packed else pa.list_(pa.int32())
        for keys, texts in text_batches(batches):
            ids = [bpe.encode_packed(t) for t in texts]
            columns = [keys, pa.array(ids if packed else [struct.unpack(f"<{len(x) // 4}I", x) for x in ids], kind), pa.array([len(x) // 4 for x in ids], pa.int64())]
            names = ["doc_id", "ids", "n_tokens"]
            if decode:
                columns.append(pa.array([bpe.decode_packed(x) for x in ids], pa.string()))
                names.append("decoded")
            yield pa.RecordBatch.from_arrays(columns, names)

    return run


def encode(docs: DataFrame, path: str | None = None, *, id_col: str = "doc_id", text_col: str = "text", packed: bool = False, decoded: bool = False) -> DataFrame:
    """doc_id, ids (array of int, or little-endian bytes if packed), n_tokens; with decoded, also the text the ids stand for.

    One scan of two columns and no shuffle; each worker loads the vocabulary once.
    """
    ship(docs.sparkSession)
    schema = f"doc_id bigint, ids {'binary' if packed else 'array<int>'}, n_tokens bigint" + ", decoded string" * decoded
    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_rows(path or default_vocabulary(), decoded, packed), schema)


def decode(encoded: DataFrame, path: str | None = None, *, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """doc_id, decoded.  A null id array counts as empty; unknown ids raise KeyError."""
    ship(encoded.sparkSession)
    path = path or default_vocabulary()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for batch in batches:
            texts = [bpe.decode(x or []) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["doc_id", "decoded"])

    return encoded.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(ids_col).cast("array<int>").alias("ids")).mapInArrow(run, "doc_id bigint, decoded string")


def digests(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every document."""
    return encode(docs, path, packed=True, decoded=True).select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"))
