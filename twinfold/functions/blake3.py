"""BLAKE3 (default mode, 256-bit output) after the public specification, vectorised over the chunks of many inputs."""

from __future__ import annotations

import numpy as np

#: Fixed values of the specification.
_IV = np.array([0x6A09E667, 0xBB67AE85, 0x3C6EF372, 0xA54FF53A, 0x510E527F, 0x9B05688C, 0x1F83D9AB, 0x5BE0CD19], np.uint32)
_PERMUTATION = [2, 6, 3, 10, 7, 0, 4, 13, 1, 11, 12, 5, 9, 14, 15, 8]
_START, _END, _PARENT, _ROOT = 1, 2, 4, 8
_BLOCK, _CHUNK = 64, 1024
_MIXES = [(0, 4, 8, 12), (1, 5, 9, 13), (2, 6, 10, 14), (3, 7, 11, 15), (0, 5, 10, 15), (1, 6, 11, 12), (2, 7, 8, 13), (3, 4, 9, 14)]


def _turn(x: np.ndarray, n: int) -> np.ndarray:
    return (x >> np.uint32(n)) | (x << np.uint32(32 - n))


def _compress(value: np.ndarray, block: np.ndarray, counter: np.ndarray, length: np.ndarray, flags: np.ndarray) -> np.ndarray:
    """Chaining values (8, n) and blocks (16, n) to new chaining values (8, n)."""
    n = value.shape[1]
    s = [*value, *(np.full(n, x, np.uint32) for x in _IV[:4]), counter.astype(np.uint32), (counter >> np.uint64(32)).astype(np.uint32), length.astype(np.uint32), flags.astype(np.uint32)]
    m = list(block)
    for r in range(7):
        for k, (a, b, c, d) in enumerate(_MIXES):
            for x, (p, q) in ((m[2 * k], (16, 12)), (m[2 * k + 1], (8, 7))):
                s[a] = s[a] + s[b] + x
                s[d] = _turn(s[d] ^ s[a], p)
                s[c] = s[c] + s[d]
                s[b] = _turn(s[b] ^ s[c], q)
        if r < 6:
            m = [m[i] for i in _PERMUTATION]
    return np.stack([s[i] ^ s[i + 8] for i in range(8)])


_AT_ONCE = 2048  # chunks whose state stays in a core's cache


def _chunks(data: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Chaining values (8, n) of the chunks of all inputs, one input after the other, and the number of chunks of each; the only chunk of a short input is its root."""
    sizes = np.array([len(x) for x in data], np.int64)
    counts = np.maximum(1, -(-sizes // _CHUNK))
    first = np.cumsum(counts) - counts
    padded = bytearray(int(counts.sum()) * _CHUNK)
    for x, at in zip(data, (first * _CHUNK).tolist()):
        padded[at : at + len(x)] = x
    words = np.frombuffer(padded, "<u4").astype(np.uint32, copy=False).reshape(-1, 16, 16)
    owner = np.repeat(np.arange(len(data)), counts)
    number = np.arange(len(owner)) - first[owner]
    lengths = np.minimum(sizes[owner] - number * _CHUNK, _CHUNK)
    root = np.where(counts[owner] == 1, _ROOT, 0)
    last = np.maximum(-(-lengths // _BLOCK), 1) - 1
    value = np.repeat(_IV[:, None], len(owner), axis=1)
    for s in range(0, len(owner), _AT_ONCE):
        for k in range(16):
            live = np.flatnonzero(last[s : s + _AT_ONCE] >= k) + s
            if not len(live):
                break
            flags = np.where(k == 0, _START, 0) + np.where(last[live] == k, _END | root[live], 0)
            value[:, live] = _compress(value[:, live], words[live, k].T, number[live].astype(np.uint64), np.clip(lengths[live] - k * _BLOCK, 0, _BLOCK), flags)
    return value, counts


def blake3_many(data: list[bytes]) -> list[bytes]:
    """Digests of many inputs: the chunks of all of them are compressed side by side, then the pairs of each level of all trees."""
    if not data:
        return []
    level, counts = _chunks(data)
    while (counts > 1).any():
        up = -(-counts // 2)
        first, owner = np.cumsum(counts) - counts, np.repeat(np.arange(len(data)), up)
        own = 2 * (np.arange(len(owner)) - (np.cumsum(up) - up)[owner])
        left = first[owner] + own
        both = np.flatnonzero(own + 1 < counts[owner])
        out = level[:, left]  # an odd last node joins one level higher
        for s in range(0, len(both), _AT_ONCE):
            at = both[s : s + _AT_ONCE]
            flags = _PARENT | np.where(counts[owner[at]] == 2, _ROOT, 0)
            n = len(at)
            out[:, at] = _compress(np.repeat(_IV[:, None], n, axis=1), np.concatenate([level[:, left[at]], level[:, left[at] + 1]]), np.zeros(n, np.uint64), np.full(n, _BLOCK), flags)
        level, counts = out, up
    whole = np.ascontiguousarray(level.T).astype("<u4").tobytes()
    return [whole[32 * i : 32 * i + 32] for i in range(len(data))]


def blake3(data: bytes) -> bytes:
    return blake3_many([data])[0]


def hex_digests(values) -> list[str | None]:
    """Digests in hexadecimal of a column of an Arrow batch; null stays null."""
    there = [i for i, x in enumerate(values) if x is not None]
    out: list[str | None] = [None] * len(values)
    for i, made in zip(there, blake3_many([bytes(values[i]) for i in there])):
        out[i] = made.hex()
    return out
