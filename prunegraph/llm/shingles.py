"""Word-shingle sets of whole texts, in numpy over Arrow buffers.

A word is a longest run of bytes other than space and the control characters tab to
carriage return, A-Z lower-cased. A shingle is ``words`` successive words; a text with
fewer has its whole word sequence as one shingle; a text without words has none."""

from __future__ import annotations

import numpy as np

from prunegraph.llm.common import cleared_after_task, mix

_seed = np.random.default_rng(20240607)
_BYTE = _seed.integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)
_FOLDED = _BYTE.copy()
_FOLDED[ord("A") : ord("Z") + 1] = _BYTE[ord("a") : ord("z") + 1]
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_R = np.uint64(0x5851F42D4C957F2D)
_R_INVERSE = np.uint64(pow(int(_R), -1, 1 << 64))
_power: dict[str, np.ndarray] = {"up": np.ones(1, np.uint64), "down": np.ones(1, np.uint64)}
#: Longest powers that outlive a task.
_LONGEST_KEPT = 1 << 17


@cleared_after_task
def _shorten() -> None:
    for name, x in _power.items():
        if len(x) > _LONGEST_KEPT:
            _power[name] = x[:_LONGEST_KEPT].copy()


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """R^0..R^(n-1) and R^0..R^-(n-1) modulo 2^64."""
    if len(_power["up"]) < n:
        for name, base in (("up", _R), ("down", _R_INVERSE)):
            x = np.full(n, base, np.uint64)
            x[0] = 1
            _power[name] = np.multiply.accumulate(x)
    return _power["up"][:n], _power["down"][:n]


def sums(raw: np.ndarray, fold: bool = False) -> np.ndarray:
    """Prefix sums P with (P[j] - P[i]) * R^-i a hash of raw[i:j]; fold: A-Z as a-z."""
    up, _ = powers(max(1, len(raw)))
    out = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum((_FOLDED if fold else _BYTE)[raw] * up[: len(raw)], out=out[1:])
    return out


def word_hashes(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hash, row) of every word of the texts in ``raw``."""
    if not len(raw):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    inside = ~_SPACE[raw]
    start = inside.copy()
    start[1:] &= ~inside[:-1]
    edge = offsets[1:-1]
    edge = edge[edge < len(raw)]
    start[edge] = inside[edge]
    starts = np.flatnonzero(start)
    stop = np.empty(len(raw), bool)  # last byte of a word
    stop[:-1] = inside[:-1] & ~inside[1:]
    stop[-1] = inside[-1]
    stop[edge[edge > 0] - 1] |= inside[edge[edge > 0] - 1]
    ends = np.flatnonzero(stop) + 1
    total = sums(raw, fold=True)
    _, down = powers(len(raw) + 1)
    h = mix((total[ends] - total[starts]) * down[starts] ^ (ends - starts).astype(np.uint64))
    return h, np.searchsorted(offsets, starts, "right") - 1


def shingle_sets(raw: np.ndarray, offsets: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes, sorted within each row, and the row offsets of the sets."""
    n = len(offsets) - 1
    h, row = word_hashes(raw, offsets)
    first = np.searchsorted(row, np.arange(n + 1))
    counts = np.diff(first)
    keep = np.arange(len(h)) + words <= first[1:][row] if len(h) else np.zeros(0, bool)
    parts = [(h * np.uint64(3) + np.uint64(1))]
    rolled = mix(parts[0])
    for k in range(1, words):
        shifted = np.zeros_like(h)
        shifted[: len(h) - k] = h[k:]
        rolled = mix(rolled * np.uint64(0x9E3779B97F4A7C15) + shifted)
    sh, sr = rolled[keep], row[keep]
    short = np.flatnonzero((counts > 0) & (counts < words))
    if len(short):
        more = np.zeros(len(short), np.uint64)
        for i, r in enumerate(short):
            x = mix(np.array([counts[r] + 17], np.uint64))
            for w in h[first[r] : first[r + 1]]:
                x = mix(x * np.uint64(0x9E3779B97F4A7C15) + w)
            more[i] = x[0]
        sh, sr = np.concatenate([sh, more]), np.concatenate([sr, short])
    order = np.lexsort((sh, sr))
    sh, sr = sh[order], sr[order]
    new = np.ones(len(sh), bool)
    new[1:] = (sh[1:] != sh[:-1]) | (sr[1:] != sr[:-1])
    sh, sr = sh[new], sr[new]
    return sh, np.searchsorted(sr, np.arange(n + 1))


def minhash(sets: np.ndarray, at: np.ndarray, n_hashes: int, seed: int = 11) -> np.ndarray:
    """(rows, n_hashes) 16-bit minima; rows with empty sets hold zeros."""
    rng = np.random.default_rng(seed)
    a = rng.integers(1, 1 << 32, n_hashes, dtype=np.uint32) | np.uint32(1)
    x = rng.integers(1, 1 << 32, n_hashes, dtype=np.uint32)
    n = len(at) - 1
    out = np.zeros((n, n_hashes), np.uint16)
    full = np.flatnonzero(np.diff(at) > 0)
    block = 1 << 15
    low = (sets >> np.uint64(32)).astype(np.uint32)
    i = 0
    while i < len(full):
        j = max(i + 1, int(np.searchsorted(at[full], at[full[i]] + block, "left")))
        j = min(j, len(full))
        part = low[at[full[i]] : at[full[j - 1] + 1]]
        cuts = at[full[i:j]] - at[full[i]]
        for k in range(n_hashes):
            m = np.minimum.reduceat((part ^ x[k]) * a[k], cuts)
            out[full[i:j], k] = ((m * np.uint32(0x9E3779B1)) >> np.uint32(16)).astype(np.uint16)
        i = j
    return out
