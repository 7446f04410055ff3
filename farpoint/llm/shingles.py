"""Hashes of the word shingles of a text."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import xxhash

SEED = 42


def shingle_hashes(text: str | None, shingle: int, seed: int = SEED) -> Iterator[np.ndarray]:
    """XXH64 of the word shingles in pieces; a text of fewer words is one shingle, one of none has none."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return
    body = b" ".join(words)
    n = max(len(words) - shingle + 1, 1)
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(sizes + 1) - 1
    starts = (ends - sizes)[:n].tolist()
    stops = ends[len(words) - n :].tolist()
    digest = xxhash.xxh64_intdigest
    for lo in range(0, n, 65_536):
        yield np.fromiter((digest(body[a:b], seed) for a, b in zip(starts[lo : lo + 65_536], stops[lo : lo + 65_536], strict=True)), np.uint64)


def majority_bits(pieces: Iterable[np.ndarray]) -> int:
    """A bit is 1 if it is set in over half of the hashes, repeats included."""
    votes, n = np.zeros(64, np.int64), 0
    for hashes in pieces:
        bits = np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        votes += np.add.reduce(bits, axis=0, dtype=np.int32)
        n += len(hashes)
    return int(np.packbits(votes * 2 > n, bitorder="little").view(np.uint64)[0])
