"""Word shingles of whole texts as sorted 64-bit hashes, and their HyperMinHash sketches."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash

WIDTH = 5
#: Sketch: 2**BUCKET_BITS registers, each a leading-zero count (6 bits) and MANTISSA bits.
BUCKET_BITS, MANTISSA = 7, 10
BUCKETS = 1 << BUCKET_BITS
REST = 64 - BUCKET_BITS
_ODD = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F], np.uint64)


def mixed(h: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit values."""
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def word_hashes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bounds, hashes): words are runs of bytes other than 0x20 and 0x09-0x0D, with A-Z lower-cased."""
    split = pc.ascii_split_whitespace(pc.ascii_lower(texts))
    bounds = split.offsets.to_numpy().astype(np.int64)
    coded = split.values.slice(bounds[0], bounds[-1] - bounds[0]).dictionary_encode()
    if not len(coded):
        return bounds - bounds[0], np.zeros(0, np.uint64)
    words, codes = coded.dictionary.to_pylist(), coded.indices.to_numpy()
    digest = xxhash.xxh3_64_intdigest
    hashes = np.fromiter((digest(w) for w in words), np.uint64, len(words))
    real = np.fromiter(map(len, words), np.int64, len(words)) > 0
    keep = real[codes]
    bounds = np.concatenate([[0], np.cumsum(keep)])[bounds - bounds[0]]
    return bounds, hashes[codes[keep]]


def shingle_sets(texts: pa.Array, width: int = WIDTH) -> list[np.ndarray]:
    """The distinct shingle hashes of each text, ascending.

    With fewer words than ``width`` the whole sequence is one shingle; without words the set is empty.
    """
    bounds, words = word_hashes(texts)
    factors = np.resize(_ODD, width) * (np.arange(width, dtype=np.uint64) * np.uint64(2) + np.uint64(1))
    n = len(words)
    full = np.zeros(max(0, n - width + 1), np.uint64)
    for k in range(width if len(full) else 0):
        full += words[k : n - width + 1 + k] * factors[k]
    full = mixed(full)
    out = []
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
        if b - a >= width:
            h = full[a : b - width + 1].copy()
            h.sort()
            out.append(h[np.concatenate([[True], h[1:] != h[:-1]])])
        elif b > a:
            out.append(mixed(np.array([(words[a:b] * factors[: b - a]).sum() + np.uint64(b - a)], np.uint64)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


_EDGES = np.arange(BUCKETS, dtype=np.uint64) << np.uint64(REST)
_SEEDS = mixed(np.arange(1, BUCKETS + 1, dtype=np.uint64)) | np.uint64(1)
#: Sets below FEW take one hash function a register, those of at least 3/4 of it one bucket a register.
#: Sets with a Jaccard similarity of 3/4 or more are of sizes within that ratio, so both have one kind.
FEW = 512


def registers(least: np.ndarray) -> np.ndarray:
    """(leading zeros + 1, mantissa) of values of REST bits, in one integer of 16 bits."""
    high = (least >> np.uint64(REST - 32)).astype(np.int64)  # 32 leading bits decide unless all are zero
    low = (least & np.uint64((1 << (REST - 32)) - 1)).astype(np.int64)
    length = np.where(high > 0, np.frexp(high.astype(np.float64))[1] + REST - 32, np.frexp(low.astype(np.float64))[1])
    zeros = (REST - length).astype(np.uint64)
    left = (least << zeros) & np.uint64((1 << (REST - 1)) - 1)  # the first one bit goes
    return ((zeros + np.uint64(1)) << np.uint64(MANTISSA) | left >> np.uint64(REST - 1 - MANTISSA)).astype(np.uint16)


def bucket_sketch(shingles: np.ndarray) -> np.ndarray:
    """Registers of an ascending set, 0 for an empty bucket.

    The bucket is a hash's top bits; the least of the rest has the most leading zeros, and its
    mantissa is what follows the first one bit.
    """
    out = np.zeros(BUCKETS, np.uint16)
    at = np.searchsorted(shingles, _EDGES)
    found = np.flatnonzero(np.diff(at, append=len(shingles)))
    out[found] = registers(shingles[at[found]] & np.uint64((1 << REST) - 1))
    return out


def function_sketch(shingles: np.ndarray) -> np.ndarray:
    """Registers of a small set: the least value under each of as many hash functions."""
    values = shingles[:, None] * _SEEDS[None, :]
    values ^= values >> np.uint64(29)
    values *= np.uint64(0xBF58476D1CE4E5B9)
    return registers(values.min(axis=0) >> np.uint64(BUCKET_BITS))


def sketches(shingles: np.ndarray) -> tuple[np.ndarray | None, np.ndarray | None]:
    """(registers by function, registers by bucket), each where the set's size asks for it."""
    n = len(shingles)
    return (function_sketch(shingles) if 0 < n < FEW else None, bucket_sketch(shingles) if 4 * n >= 3 * FEW else None)


def chance_matches(n: np.ndarray, m: np.ndarray) -> np.ndarray:
    """The share of registers that agree by chance between disjoint sets that put n and m elements in each.

    Both least values must fall in one leading-zero class and share the mantissa bits there.
    """
    a, b = np.asarray(n, float)[..., None], np.asarray(m, float)[..., None]
    level = np.arange(REST)
    low, high = 2.0 ** -(level + 1), 2.0**-level
    in_level = lambda x: np.exp(-x * low) - np.exp(-x * high)
    return (in_level(a) * in_level(b)).sum(-1) * 2.0**-MANTISSA


def estimated_jaccard(a: np.ndarray, b: np.ndarray, n: np.ndarray, m: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(estimates, filled registers) by row: agreeing registers, less those expected by chance, of the filled.

    n and m are elements a register: set sizes by function, set sizes over BUCKETS by bucket.
    """
    filled = ((a > 0) | (b > 0)).sum(-1)
    same = ((a == b) & (a > 0)).sum(-1) / np.maximum(filled, 1)
    chance = chance_matches(n, m)
    return np.clip((same - chance) / (1 - chance), 0, 1), filled
