"""The portable hash for whole columns: md5 of many short messages at once, the same 52 bits as ``hashing.bits``."""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa

U = np.uint32
_BEGIN = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
_TURN = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
#: (constant, word, shift left, shift right) of each of the 64 steps
_STEPS = [(U(int(abs(math.sin(i + 1)) * 2**32)), (i, 5 * i + 1, 3 * i + 5, 7 * i)[i >> 4] & 15, U(_TURN[i >> 4][i & 3]), U(32 - _TURN[i >> 4][i & 3])) for i in range(64)]
#: messages done at once: a call of numpy is short beside them
AT_ONCE = 1 << 16
#: bytes of a text in the arrays; longer ones are done one by one
SHORT = 180


def _block(state: list[np.ndarray], words: list[np.ndarray | None]) -> list[np.ndarray]:
    """The state after one more block of 16 words; None: a word that is 0 in all messages."""
    a, b, c, d = (s.copy() for s in state)
    f = np.empty_like(a)
    for i, (constant, word, left, right) in enumerate(_STEPS):
        if i < 16:
            np.bitwise_xor(c, d, f), np.bitwise_and(f, b, f), np.bitwise_xor(f, d, f)
        elif i < 32:
            np.bitwise_xor(b, c, f), np.bitwise_and(f, d, f), np.bitwise_xor(f, c, f)
        elif i < 48:
            np.bitwise_xor(b, c, f), np.bitwise_xor(f, d, f)
        else:
            np.invert(d, f), np.bitwise_or(f, b, f), np.bitwise_xor(f, c, f)
        np.add(a, f, a), np.add(a, constant, a)
        if words[word] is not None:
            np.add(a, words[word], a)
        np.left_shift(a, left, f), np.right_shift(a, right, a), np.bitwise_or(a, f, a), np.add(a, b, a)
        a, b, c, d = d, a, b, c
    return [s + t for s, t in zip(state, (a, b, c, d), strict=True)]


def _hashed(padded: np.ndarray, size: np.ndarray) -> np.ndarray:
    """52 bits of messages that take the same blocks: rows of their bytes, 0x80 and zeros, and their sizes."""
    state = [np.full(len(size), v, U) for v in _BEGIN]
    blocks = (int(size[0]) + 8) // 64 + 1
    columns = padded.view("<u4")
    for at in range(blocks):
        words: list[np.ndarray | None] = [None] * 16
        for k in range(16 * at, min(16 * at + 16, columns.shape[1])):
            column = np.ascontiguousarray(columns[:, k])
            words[k - 16 * at] = column if column.any() else None
        if at == blocks - 1:
            words[14] = (size * 8).astype(U)
        state = _block(state, words)
    return (state[0].byteswap().astype(np.int64) << 20) | (state[1].byteswap() >> U(12))


def _short(data: np.ndarray, begin: np.ndarray, length: np.ndarray, head: bytes, tails: list[bytes]) -> np.ndarray:
    """(texts, tails) for texts of one slice."""
    n, k = len(length), len(tails)
    width = -(-(len(head) + int(length.max(initial=0)) + max(map(len, tails)) + 1) // 4) * 4
    one = np.zeros((n, width), np.uint8)
    one[:, : len(head)] = np.frombuffer(head, np.uint8)
    inside = np.arange(int(length.sum())) - np.repeat(np.cumsum(length) - length, length)
    one.reshape(-1)[np.repeat(np.arange(n) * width + len(head), length) + inside] = data[np.repeat(begin, length) + inside]
    whole = np.repeat(one, k, axis=0)
    place = np.arange(n * k) * width + np.repeat(len(head) + length, k)
    ends = [t + b"\x80" for t in tails]
    for i in range(max(map(len, ends))):
        byte = np.array([t[i] if i < len(t) else 0 for t in ends], np.uint8)
        # a shorter end's place may lie behind the row's: it has nothing to say there
        has = np.tile(np.array([i < len(t) for t in ends]), n)
        if has.all():
            whole.reshape(-1)[place + i] = np.tile(byte, n)
        else:
            whole.reshape(-1)[place[has] + i] = np.tile(byte, n)[has]
    size = np.repeat(len(head) + length, k) + np.tile(np.array([len(t) for t in tails]), n)
    blocks = (size + 8) // 64
    if (blocks == blocks[0]).all():
        return _hashed(whole, size).reshape(n, k)
    out = np.empty(n * k, np.int64)
    for b in np.unique(blocks):
        out[blocks == b] = _hashed(whole[blocks == b], size[blocks == b])
    return out.reshape(n, k)


def bits52(texts: pa.Array, head: bytes, tails: list[bytes]) -> np.ndarray:
    """52 bits of the md5 of head, text and tail as an array (texts, tails), for texts without null."""
    texts = texts.cast(pa.large_string())
    n = len(texts)
    _, offsets, data = texts.buffers()
    edge = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + n + 1] if n else np.zeros(1, np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    length = np.diff(edge)
    out = np.empty((n, len(tails)), np.int64)
    # texts of like length stand together, so that a slice is no wider than it must be
    order = np.argsort(length, kind="stable")
    few = int(np.searchsorted(length[order], SHORT, "right"))
    step = max(1, AT_ONCE // len(tails))
    for i in range(0, few, step):
        rows = order[i : min(i + step, few)]
        out[rows] = _short(data, edge[rows], length[rows], head, tails)
    for i in order[few:]:
        begun = hashlib.md5(head + data[edge[i] : edge[i + 1]].tobytes(), usedforsecurity=False)
        for k, tail in enumerate(tails):
            whole = begun.copy()
            whole.update(tail)
            out[i, k] = int.from_bytes(whole.digest()[:7], "big") >> 4
    return out
