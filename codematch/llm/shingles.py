"""Word shingles as sorted arrays of 64-bit hashes, in numpy; shared by the similarity join and its tests."""

from __future__ import annotations

import numpy as np
import xxhash

#: Odd multipliers of the shingle and mixing hashes; any odd numbers do.
_MIX1, _MIX2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_ROLE = [np.uint64(0x9E3779B97F4A7C15 + 2 * i * 0x632BE59BD9B4E019 & 0xFFFFFFFFFFFFFFFF | 1) for i in range(64)]


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit."""
    x = x ^ np.uint64(salt & 0xFFFFFFFFFFFFFFFF)
    x = (x ^ (x >> np.uint64(30))) * _MIX1
    x = (x ^ (x >> np.uint64(27))) * _MIX2
    return x ^ (x >> np.uint64(31))


#: Words of more bytes are hashed one by one, texts of fewer bytes by the table of words; the hash of a word is the same on each way.
_LONG, _SHORT = 32, 200
_STEP = 0x9E3779B97F4A7C15
_SPACE = bytes(c in b" \t\n\r\x0b\x0c" for c in range(256))
#: Masks of the first 0 to 8 bytes of a little-endian word.
_FIRST = np.array([(1 << 8 * i) - 1 for i in range(9)], np.uint64)


def _mix_int(x: int) -> int:
    x = (x ^ x >> 30) * int(_MIX1) & 0xFFFFFFFFFFFFFFFF
    x = (x ^ x >> 27) * int(_MIX2) & 0xFFFFFFFFFFFFFFFF
    return x ^ x >> 31


def word_hash(word: bytes) -> int:
    """64-bit hash of a word: its length and its runs of 8 bytes, mixed one after another."""
    if len(word) > _LONG:
        return xxhash.xxh3_64_intdigest(word)
    h = _mix_int(len(word))
    for at in range(0, len(word), 8):
        h = _mix_int(h * _STEP + int.from_bytes(word[at : at + 8], "little") & 0xFFFFFFFFFFFFFFFF)
    return h


def word_hashes(text: bytes) -> np.ndarray:
    """word_hash of each word of a text, in its order, without a Python object for each word."""
    padded = b" " + text + b" " * 8
    space = np.frombuffer(padded.translate(_SPACE), np.int8)
    bound = np.flatnonzero(space[1:] != space[:-1]) + 1
    start, stop = bound[::2], bound[1::2]
    size = stop - start
    runs = np.ndarray(len(text) + 2, "<u8", padded, strides=(1,))
    h = _LENGTH[np.minimum(size, _LONG)]
    longest = int(size.max(initial=0))
    for at in range(0, min(longest, _LONG), 8):
        own = slice(None) if at == 0 else np.flatnonzero(size > at)
        run = runs[start[own] + at] & _FIRST[np.minimum(size[own] - at, 8)]
        h[own] = mix(h[own] * np.uint64(_STEP) + run)
    if longest > _LONG:
        for i in np.flatnonzero(size > _LONG):
            h[i] = xxhash.xxh3_64_intdigest(padded[start[i] : stop[i]])
    return h


#: Where the hash of a word of so many bytes begins.
_LENGTH = mix(np.arange(_LONG + 1, dtype=np.uint64))


class WordHashes(dict):
    """word -> its hash; emptied when it has grown large, so a worker's memory stays bounded."""

    LIMIT = 100_000

    def __missing__(self, word: bytes) -> int:
        if len(self) > self.LIMIT:
            self.clear()
        value = self[word] = word_hash(word)
        return value


def shingle_set(text: bytes | None, width: int, cache: WordHashes) -> np.ndarray:
    """Sorted distinct hashes of the runs of `width` words of a UTF-8 text.

    A-Z are lower-cased; words are runs of anything but the six ASCII spaces. With fewer
    words than `width` the whole sequence is the only shingle; without words the set is empty.
    """
    text = text.lower() if text else b""
    if len(text) < _SHORT:
        words = text.split()
        one = np.fromiter(map(cache.__getitem__, words), np.uint64, len(words))
    else:
        one = word_hashes(text)
    if not len(one):
        return np.empty(0, np.uint64)
    if len(one) < width:
        return np.array([xxhash.xxh3_64_intdigest(b" ".join(text.split()), seed=len(one))], np.uint64)
    n = len(one) - width + 1
    total = one[:n] * _ROLE[0]
    for i in range(1, width):
        total += one[i : i + n] * _ROLE[i]
    total = mix(total)
    total.sort()
    new = np.empty(n, bool)
    new[0] = True
    np.not_equal(total[1:], total[:-1], out=new[1:])
    return total[new]


def set_digest(s: np.ndarray) -> tuple[int, int]:
    """Two 64-bit digests of a set, as signed integers; equal sets have equal digests."""
    if not len(s):
        return 0, 0
    one, two = int(mix(s, 0x1234567).sum(dtype=np.uint64)), int(mix(s, 0x7654321).sum(dtype=np.uint64))
    return one - (one >> 63 << 64), two - (two >> 63 << 64)
