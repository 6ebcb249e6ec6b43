"""Byte-level BPE encoding and decoding.

A pre-token's parts live in two contiguous arrays: the borders of its parts and
the merge rank of each adjacent pair.  The smallest rank (leftmost on ties) is
found by scanning, its right border deleted, and the two neighbouring ranks
looked up anew.  Long pre-tokens take the same merges in the same order from a
heap over linked borders, so no text makes the scan quadratic.
"""

from __future__ import annotations

import hashlib
import heapq
import json

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCAN_LIMIT = 256
CACHE_ENTRIES = 400_000
CACHED_BYTES = 64
_NEVER = 1 << 60


def byte_letters() -> dict[str, int]:
    """The printable stand-in of each byte in byte-level vocabularies."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    letters = {chr(b): b for b in shown}
    spare = 0
    for b in range(256):
        if b not in shown:
            letters[chr(256 + spare)] = b
            spare += 1
    return letters


class ByteBpe:
    """A byte-level BPE vocabulary in the public ``tokenizers`` JSON format."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = byte_letters()
        to_bytes = lambda s: bytes(letters[c] for c in s)
        self.ids = {to_bytes(s): i for s, i in spec["model"]["vocab"].items()}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.pieces: list[bytes] = [b""] * (1 + max([*self.ids.values(), *self.special.values()]))
        for b, i in self.ids.items():
            self.pieces[i] = b
        for s, i in self.special.items():
            self.pieces[i] = s.encode()
        self.ranks: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, merge in enumerate(spec["model"]["merges"]):
            left, right = merge.split(" ") if isinstance(merge, str) else merge
            left, right = to_bytes(left), to_bytes(right)
            self.ranks[self.ids[left], self.ids[right]] = (rank, self.ids[left + right])
        self.single = [self.ids[bytes([b])] for b in range(256)]
        # Fixed value: the public byte-level pre-token pattern.
        self.pattern = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+")
        self.splitter = regex.compile("(" + "|".join(regex.escape(s) for s in sorted(self.special, key=len, reverse=True)) + ")") if self.special else None
        self.cache = _Cache(self)

    def merge(self, word: bytes) -> list[int]:
        """Token ids of one pre-token."""
        parts = [self.single[b] for b in word]
        if len(parts) < 2:
            return parts
        if len(parts) > SCAN_LIMIT:
            return self._merge_long(parts)
        get = self.ranks.get
        none = (_NEVER, -1)
        pairs = [get(p, none) for p in zip(parts, parts[1:], strict=False)]
        while pairs:
            best = min(pairs)
            if best[0] == _NEVER:
                break
            at = pairs.index(best)
            parts[at] = best[1]
            del parts[at + 1]
            del pairs[at]
            if at < len(pairs):
                pairs[at] = get((parts[at], parts[at + 1]), none)
            if at:
                pairs[at - 1] = get((parts[at - 1], parts[at]), none)
        return parts

    def _merge_long(self, parts: list[int]) -> list[int]:
        n = len(parts)
        left, right = list(range(-1, n - 1)), list(range(1, n + 1))
        get = self.ranks.get
        heap = []
        for i in range(n - 1):
            if found := get((parts[i], parts[i + 1])):
                heap.append((found[0], i, parts[i], parts[i + 1], found[1]))
        heapq.heapify(heap)
        while heap:
            _, i, a, b, new = heapq.heappop(heap)
            j = right[i]
            if parts[i] != a or j >= n or parts[j] != b:
                continue
            parts[i], parts[j] = new, -1
            right[i] = right[j]
            if right[j] < n:
                left[right[j]] = i
            for x, y in ((left[i], i), (i, right[i])):
                if x >= 0 and y < n and (found := get((parts[x], parts[y]))):
                    heapq.heappush(heap, (found[0], x, parts[x], parts[y], found[1]))
        return [p for p in parts if p >= 0]

    def encode_bytes(self, text: str) -> bytes:
        """Ids of a text as little-endian unsigned 32-bit integers."""
        look = self.cache.__getitem__
        if self.splitter is None or not any(s in text for s in self.special):
            return b"".join(map(look, self.pattern.findall(text)))
        out = []
        for piece in self.splitter.split(text):
            if piece in self.special:
                out.append(np.array([self.special[piece]], "<u4").tobytes())
            elif piece:
                out.append(b"".join(map(look, self.pattern.findall(piece))))
        return b"".join(out)

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.encode_bytes(text), "<u4").tolist()

    def decode(self, ids) -> str:
        return b"".join(map(self.pieces.__getitem__, ids)).decode("utf-8", "replace")


class _Cache(dict):
    """Packed ids of short pre-tokens; emptied when full, so its memory is bounded."""

    def __init__(self, codec: ByteBpe):
        super().__init__()
        self.codec = codec

    def __missing__(self, word: str) -> bytes:
        raw = word.encode("utf-8", "surrogatepass")
        packed = np.array(self.codec.merge(raw), "<u4").tobytes()
        if len(raw) <= CACHED_BYTES:
            if len(self) >= CACHE_ENTRIES:
                self.clear()
            self[word] = packed
        return packed


_LOADED: dict[str, ByteBpe] = {}


def codec(path: str) -> ByteBpe:
    """The vocabulary at ``path``, loaded once per Python worker."""
    if path not in _LOADED:
        _LOADED[path] = ByteBpe(path)
    return _LOADED[path]


def _round_trip_kernel(path: str, text: str, doc_id: str, full: bool):
    def run(batches):
        bpe = codec(path)
        pieces = bpe.pieces.__getitem__
        for batch in batches:
            ids_at, text_at = batch.schema.get_field_index(doc_id), batch.schema.get_field_index(text)
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                counts, digests, decoded, kept, plain = [], [], [], [], []
                for value in part.column(text_at).to_pylist():
                    packed = bpe.encode_bytes(value or "")
                    counts.append(len(packed) // 4)
                    digests.append(hashlib.sha256(packed).hexdigest())
                    tokens = np.frombuffer(packed, "<u4").tolist()
                    back = b"".join(map(pieces, tokens)).decode("utf-8", "replace")
                    decoded.append(hashlib.sha256(back.encode("utf-8")).hexdigest())
                    if full:
                        kept.append(tokens)
                        plain.append(back)
                columns = [part.column(ids_at), pa.array(counts, pa.int64()), pa.array(digests, pa.string()), pa.array(decoded, pa.string())]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
                if full:
                    columns += [pa.array(kept, pa.list_(pa.int32())), pa.array(plain, pa.string())]
                    names += ["ids", "decoded"]
                yield pa.RecordBatch.from_arrays(columns, names=names)

    return run


def round_trip(spark: SparkSession, docs: DataFrame, path: str, text: str = "text", doc_id: str = "doc_id", full: bool = False) -> DataFrame:
    """Encode and decode every whole text: doc_id, n_tokens, ids_sha256, decoded_sha256 (+ ids, decoded).

    Null text counts as empty; empty text has no tokens; repeated rows give
    repeated results; an empty table gives no rows; extra columns are ignored.
    Special strings of the vocabulary inside a text become their own ids.  One
    narrow pass, no shuffle.
    """
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<int>, decoded string" if full else "")
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    return rows.mapInArrow(_round_trip_kernel(path, "text", "doc_id", full), schema)
