"""hashing.md5_value for whole arrays: md5 of many short messages at once, in numpy.

Messages fit in one block, as '<seed>:' and a gram or a decimal number do. A block's words are arrays over the
messages, or one number where all messages have the same word; windows of a text need no copy of their letters,
as a word of a window is a word of the text.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401

LETTERS = np.frombuffer(b"ACGT", np.uint8)
#: Messages handled at once, so that the state stays in the processor's cache.
CHUNK = 1 << 15
_K = [int(abs(math.sin(i + 1)) * (1 << 32)) & 0xFFFFFFFF for i in range(64)]
_TURN = [(7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)


def _first_words(words: list, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first two words of the md5 of n messages, from the 16 words of their blocks."""
    a, b, c, d = (np.full(n, s, np.uint32) for s in _START)
    f, g = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        turn = i // 16
        if turn == 0:  # (b & c) | (~b & d)
            np.bitwise_xor(c, d, out=f)
            np.bitwise_and(f, b, out=f)
            np.bitwise_xor(f, d, out=f)
            w = i
        elif turn == 1:  # (d & b) | (~d & c)
            np.bitwise_xor(b, c, out=f)
            np.bitwise_and(f, d, out=f)
            np.bitwise_xor(f, c, out=f)
            w = (5 * i + 1) % 16
        elif turn == 2:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
            w = (3 * i + 5) % 16
        else:  # c ^ (b | ~d)
            np.invert(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
            w = 7 * i % 16
        word = words[w]
        np.add(a, f, out=a)
        if isinstance(word, int):
            np.add(a, np.uint32((word + _K[i]) & 0xFFFFFFFF), out=a)
        else:
            np.add(a, word, out=a)
            np.add(a, np.uint32(_K[i]), out=a)
        by = _TURN[turn][i % 4]
        np.left_shift(a, np.uint32(by), out=g)
        np.right_shift(a, np.uint32(32 - by), out=a)
        np.bitwise_or(a, g, out=a)
        np.add(a, b, out=a)
        a, b, c, d = d, a, b, c
    return a + np.uint32(_START[0]), b + np.uint32(_START[1])


def _number(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """The first 15 hex digits of the digest as a number."""
    return (first.byteswap().astype(np.int64) << 28) | (second.byteswap() >> np.uint32(4)).astype(np.int64)


def of_windows(letters: np.ndarray, width: int, seed: int) -> np.ndarray:
    """Values of all substrings of `width` letters (bytes) of a text, in their order."""
    n = len(letters) - width + 1
    if n <= 0:
        return np.empty(0, np.int64)
    prefix = f"{seed}:".encode()
    p = len(prefix)
    size = p + width
    if size > 55:
        raise ValueError("a message and its seed have 55 bytes at most")
    at = np.zeros(len(letters) + 4, np.uint32)  # four letters from each place on
    raw = np.concatenate([letters, np.zeros(8, np.uint8)]).astype(np.uint32)
    for j in range(4):
        at |= raw[j : j + len(at)] << np.uint32(8 * j)
    out = np.empty(n, np.int64)
    for lo in range(0, n, CHUNK):
        hi = min(n, lo + CHUNK)
        words: list = [0] * 16
        words[14] = 8 * size
        for w in range(size // 4 + 1):
            head = sum(prefix[4 * w + j] << (8 * j) for j in range(4) if 4 * w + j < p)
            tail = 0x80 << (8 * (size - 4 * w)) if 4 * w <= size < 4 * w + 4 else 0
            first, last = max(4 * w, p), min(4 * w + 4, size)  # bytes of the word that are letters
            if first >= last:
                words[w] = head | tail
                continue
            got = at[lo + first - p : hi + first - p]
            if last - first < 4:
                got = (got & np.uint32((1 << (8 * (last - first))) - 1)) << np.uint32(8 * (first - 4 * w)) | np.uint32(head | tail)
            words[w] = got
        out[lo:hi] = _number(*_first_words(words, hi - lo))
    return out


def of_longs(values: np.ndarray, seed: int) -> np.ndarray:
    """Values of the decimal texts of non-negative longs."""
    out = np.empty(len(values), np.int64)
    for lo in range(0, len(values), CHUNK):
        text = pa.compute.ascii_rpad(pa.array(values[lo : lo + CHUNK], pa.int64()).cast(pa.string()), 20, "\0")
        text = np.frombuffer(text.buffers()[2], np.uint8, 20 * len(text)).reshape(-1, 20)
        out[lo : lo + CHUNK] = _of_texts(text, (text != 0).sum(axis=1), seed)
    return out


def of_packed(values: np.ndarray, width: int, seed: int) -> np.ndarray:
    """Values of the letters of packed grams, two bits a letter, the first letter highest."""
    out = np.empty(len(values), np.int64)
    for lo in range(0, len(values), CHUNK):
        part = values[lo : lo + CHUNK]
        text = np.empty((len(part), width), np.uint8)
        for j in range(width):
            text[:, j] = part >> (2 * (width - 1 - j)) & 3
        out[lo : lo + CHUNK] = _of_texts(LETTERS[text], np.full(len(part), width), seed)
    return out


def _of_texts(text: np.ndarray, sizes: np.ndarray, seed: int) -> np.ndarray:
    """Values of rows of letters (bytes), each with its size; bytes behind the size are 0."""
    prefix = np.frombuffer(f"{seed}:".encode(), np.uint8)
    p, (n, width) = len(prefix), text.shape
    if p + width > 55:
        raise ValueError("a message and its seed have 55 bytes at most")
    block = np.zeros((n, (p + width) // 4 * 4 + 4), np.uint8)
    block[:, :p] = prefix
    block[:, p : p + width] = text
    block[np.arange(n), p + sizes] = 0x80
    words: list = list(np.ascontiguousarray(block.view("<u4").T))
    words += [0] * (16 - len(words))
    words[14] = (8 * (p + sizes)).astype(np.uint32)
    return _number(*_first_words(words, n))
