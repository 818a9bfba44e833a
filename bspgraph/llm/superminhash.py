"""SuperMinHash signatures over word shingles, vectorised across documents.

Each set element holds a pseudo-random permutation of the signature slots and
one uniform value per rank.  Slot ``s`` of a document keeps the least
``rank + value`` over its elements, where ``rank`` is the position of ``s`` in
the element's permutation.  Ranks of one element are distinct, so the slots
are negatively correlated and the estimate has a lower variance than with
independent hash functions.

Rank layers are visited in order and a document leaves the loop as soon as all
of its slots are set (early stopping): a later layer cannot hold a smaller
value.  The permutation is a keyed bijection on the slot numbers, so the
element at any rank is found without storing the permutation.
"""

from __future__ import annotations

import numpy as np
import xxhash

SLOTS = 128
BANDS = 32
ROWS = SLOTS // BANDS
SHINGLE_WORDS = 5

_U = np.uint64
_P1, _P2, _P3 = _U(0x9E3779B97F4A7C15), _U(0xBF58476D1CE4E5B9), _U(0x94D049BB133111EB)
_EMPTY = _U(0xFFFFFFFFFFFFFFFF)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (splitmix constants)."""
    x = (x ^ (x >> _U(30))) * _P2
    x = (x ^ (x >> _U(27))) * _P3
    return x ^ (x >> _U(31))


def shingles(text: str | None, width: int = SHINGLE_WORDS) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word shingles of a whole text.

    Words are runs of bytes other than ASCII white space, with A-Z lowered.  A
    text with fewer words than ``width`` has its whole word sequence as its
    only shingle; null or wordless texts have none.
    """
    words = (text or "").encode().lower().split()
    n = len(words)
    if n == 0:
        return np.empty(0, dtype=_U)
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, words), dtype=_U, count=n)
    take = min(n, width)
    acc = h[: n - take + 1].copy()
    for i in range(1, take):
        acc = mix64(acc * _P1 + h[i : n - take + 1 + i])
    return np.unique(mix64(acc ^ _U(take)))


def _slot_at(keys: np.ndarray, rank: int, slots: int) -> np.ndarray:
    """The slot that each element's keyed permutation puts at ``rank``."""
    mask, half = _U(slots - 1), _U(max(1, (slots.bit_length() - 1) // 2))
    x = np.full(len(keys), rank, dtype=_U)
    for r in range(3):
        part = keys >> _U(20 * r)
        x = (x * (part | _U(1)) + (part >> _U(9))) & mask
        x ^= x >> half
    return x


def signatures(sets: list[np.ndarray], slots: int = SLOTS) -> np.ndarray:
    """One row of ``slots`` values per set; all ones bits for an empty set."""
    docs = len(sets)
    out = np.full(docs * slots, _EMPTY, dtype=_U)
    sizes = np.fromiter(map(len, sets), dtype=np.int64, count=docs)
    if not sizes.sum():
        return out.reshape(docs, slots)
    keys = mix64(np.concatenate(sets) + _P1)
    steps = np.arange(1, slots + 1, dtype=_U) * _P3
    owner = np.repeat(np.arange(docs, dtype=np.int64), sizes)
    for rank in range(slots):
        where = owner * slots + _slot_at(keys, rank, slots).astype(np.int64)
        value = (mix64(keys + steps[rank]) >> _U(8)) | (_U(rank) << _U(56))
        open_ = out[where] > value
        np.minimum.at(out, where[open_], value[open_])
        unfilled = (out.reshape(docs, slots) == _EMPTY).any(axis=1)
        going = unfilled[owner]
        if not going.any():
            break
        if not going.all():
            keys, owner = keys[going], owner[going]
    return out.reshape(docs, slots)


def band_keys(signature_rows: np.ndarray, bands: int = BANDS) -> np.ndarray:
    """One 64-bit key per band and row, distinct between bands."""
    docs, slots = signature_rows.shape
    parts = signature_rows.reshape(docs, bands, slots // bands)
    acc = np.broadcast_to(np.arange(1, bands + 1, dtype=_U) * _P2, (docs, bands)).copy()
    for r in range(slots // bands):
        acc = mix64(acc * _P1 + parts[:, :, r])
    return acc


def similar(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """Whether 100 * |a & b| >= percent * |a | b| for sorted distinct arrays."""
    if not len(a) or not len(b) or 100 * min(len(a), len(b)) < percent * max(len(a), len(b)):
        return False
    small, large = (a, b) if len(a) < len(b) else (b, a)
    at = np.searchsorted(large, small)
    at[at == len(large)] = 0
    both = int((large[at] == small).sum())
    return 100 * both >= percent * (len(a) + len(b) - both)
