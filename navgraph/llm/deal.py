"""Questions and answers between chunks of documents and buckets of hashes.

Documents are dealt into chunks of a few megabytes of text, hashes into buckets by their leading bits. A chunk asks every
bucket about the distinct hashes it holds, in one binary value; the bucket, which sees what all chunks hold, answers each of
them in the order of asking; and the chunk's documents meet the answers. A hash crosses the network once per chunk, a frequent
one too, so no task holds more than a chunk or a bucket, whatever the documents look like. Nothing is broadcast.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from navgraph.session import plan_bytes

#: Bytes of text that a bucket's hashes stand for, and the least and most buckets (as powers of two).
BUCKET_BYTES, LEAST_BITS, MOST_BITS = 32 << 20, 8, 18
#: Bytes of text in a chunk: at least, at most; between, so many that a bucket gets some dozens of hashes from each.
CHUNK_BYTES, MOST_CHUNK_BYTES = 4 << 20, 64 << 20


@dataclass(frozen=True)
class Deal:
    chunks: int
    bits: int

    def chunk(self, *columns: str) -> Column:
        """The chunk of a row, from the hash of these columns."""
        return F.pmod(F.xxhash64(*columns), F.lit(self.chunks)).cast("int")


def text_bytes(docs: DataFrame) -> int:
    """About the bytes of column text: from the sizes of files, as Catalyst has them (columns compress about four times); only
    where it has none, by reading."""
    some = docs.select("text")
    n = plan_bytes(some)
    return 4 * n if n is not None else int(some.agg(F.sum(F.octet_length("text"))).first()[0] or 0)


def deal_of(docs: DataFrame) -> Deal:
    size = text_bytes(docs)
    bits = min(MOST_BITS, max(LEAST_BITS, (size // BUCKET_BYTES).bit_length()))
    return Deal(size // min(MOST_CHUNK_BYTES, max(CHUNK_BYTES, 400 << bits)) + 1, bits)


def mask(bits: int, width: int) -> np.uint64:
    """The leading bits of a hash that a blob of `width` bytes a hash keeps."""
    kept = min(64, bits + 8 * width)
    return np.uint64(((1 << kept) - 1) << (64 - kept))


def bucket_of(hashes: np.ndarray, bits: int) -> np.ndarray:
    return (hashes >> np.uint64(64 - bits)).astype(np.int64)


def cuts(ascending: np.ndarray, bits: int) -> np.ndarray:
    """Where each bucket begins in ascending hashes, and the end."""
    edges = np.arange(1, 1 << bits, dtype=np.uint64) << np.uint64(64 - bits)
    return np.concatenate(([0], np.searchsorted(ascending, edges), [len(ascending)]))


def firsts(*ascending: np.ndarray) -> np.ndarray:
    """Places where sorted rows differ from the one before."""
    if not len(ascending[0]):
        return np.zeros(0, np.int64)
    new = np.zeros(len(ascending[0]), bool)
    new[0] = True
    for x in ascending:
        new[1:] |= x[1:] != x[:-1]
    return np.flatnonzero(new)


def counted(hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashes, ascending, and how often each occurs."""
    hashes = np.sort(hashes)
    first = firsts(hashes)
    return hashes[first], np.diff(np.append(first, len(hashes)))


def pack(hashes: np.ndarray, counts: np.ndarray | None, bits: int, width: int) -> bytes:
    """Ascending hashes of one bucket, `width` bytes each (4, 5 or 8), and counts; those of one take no room."""
    more = np.flatnonzero(counts != 1) if counts is not None else np.zeros(0, np.int64)
    head = np.array([len(hashes), len(more)], np.uint32).tobytes()
    if width == 8:
        body = hashes.tobytes()
    else:
        own = hashes >> np.uint64(64 - bits - 8 * width)
        body = (own & np.uint64(0xFFFFFFFF)).astype(np.uint32).tobytes()
        if width == 5:
            body += ((own >> np.uint64(32)) & np.uint64(0xFF)).astype(np.uint8).tobytes()
    return head + body + more.astype(np.uint32).tobytes() + (counts[more].astype(np.uint32).tobytes() if len(more) else b"")


def unpack(blob: bytes, bucket: int, bits: int, width: int) -> tuple[np.ndarray, np.ndarray]:
    n, more = (int(x) for x in np.frombuffer(blob, np.uint32, 2))
    at = 8 + width * n
    if width == 8:
        hashes = np.frombuffer(blob, np.uint64, n, 8)
    else:
        hashes = np.frombuffer(blob, np.uint32, n, 8).astype(np.uint64)
        if width == 5:
            hashes |= np.frombuffer(blob, np.uint8, n, 8 + 4 * n).astype(np.uint64) << np.uint64(32)
        hashes = hashes << np.uint64(64 - bits - 8 * width) | np.uint64(bucket) << np.uint64(64 - bits)
    counts = np.ones(n, np.int64)
    counts[np.frombuffer(blob, np.uint32, more, at)] = np.frombuffer(blob, np.uint32, more, at + 4 * more)
    return hashes, counts


def packed(hashes: np.ndarray, counts: np.ndarray | None, bits: int, width: int) -> tuple[list[int], list[bytes]]:
    """Ascending hashes as (bucket, blob), without empty ones."""
    at = cuts(hashes, bits)
    found = np.flatnonzero(np.diff(at))
    return found.tolist(), [pack(hashes[at[b] : at[b + 1]], None if counts is None else counts[at[b] : at[b + 1]], bits, width) for b in found]


def totals(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """From several (hashes, counts): distinct hashes, the sum of counts of each, and the place of every given hash among them."""
    if not parts:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    hashes, counts = (np.concatenate(x) for x in zip(*parts, strict=True))
    order = np.argsort(hashes, kind="stable")
    own = hashes[order]
    first = firsts(own)
    place = np.empty(len(hashes), np.int64)
    place[order] = np.repeat(np.arange(len(first)), np.diff(np.append(first, len(own))))
    return own[first], np.add.reduceat(counts[order], first) if len(first) else counts, place
