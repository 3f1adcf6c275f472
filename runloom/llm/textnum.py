"""Words and word n-grams of many texts at once, as numpy arrays over UTF-8 bytes.

A word is a longest run of word bytes. Both word classes used here keep every byte of a
multi-byte character (0x80 and above), so splitting bytes equals splitting characters.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from runloom.llm.common import PIECE

_MULT = np.uint64(0x9E3779B97F4A7C15)
_INV = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))


def byte_class(separators: list[tuple[int, int]]) -> np.ndarray:
    """256 booleans: True for word bytes, False inside the given inclusive ranges."""
    out = np.ones(256, bool)
    for low, high in separators:
        out[low : high + 1] = False
    return out


#: [^\x20\x09-\x0D]+
SPACED = byte_class([(0x20, 0x20), (0x09, 0x0D)])
#: [^\x00-\x2F\x3A-\x60\x7B-\x7F]+
ALNUM = byte_class([(0x00, 0x2F), (0x3A, 0x60), (0x7B, 0x7F)])
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        size = max(n, PIECE + (PIECE >> 2))
        for k, base in enumerate((_MULT, _INV)):
            steps = np.full(size, base)
            steps[0] = 1
            _powers[k] = np.cumprod(steps, dtype=np.uint64)
    return _powers[0], _powers[1]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit integers (the splitmix64 finaliser)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


@dataclass
class Words:
    """Words of a piece of texts in order: byte start and end in buf, text number, 64-bit hash."""

    buf: np.ndarray
    start: np.ndarray
    end: np.ndarray
    text: np.ndarray
    hash: np.ndarray
    first: np.ndarray  # n texts + 1: number of the first word of each text

    def bytes(self, k: int) -> bytes:
        return self.buf[self.start[k] : self.end[k]].tobytes()


def words(buf: np.ndarray, offs: np.ndarray, kind: np.ndarray, lower: bool = True) -> Words:
    """Words of the texts buf[offs[i]:offs[i+1]]; lower maps A-Z only. Memory for hashing stays at PIECE bytes of text."""
    if lower:
        buf = LOWER[buf]
    n = len(buf)
    inside = np.zeros(n + 2, bool)
    inside[1:-1] = kind[buf]
    edge = np.zeros(n + 1, bool)
    edge[offs] = True
    start = np.flatnonzero(inside[1:] & (~inside[:-1] | edge))
    end = np.flatnonzero(inside[:-1] & (~inside[1:] | edge))
    first = np.searchsorted(start, offs)
    text = np.repeat(np.arange(len(offs) - 1), np.diff(first))
    out = np.empty(len(start), np.uint64)
    done = 0
    while done < len(start):
        stop = max(done + 1, int(np.searchsorted(end, start[done] + PIECE, "right")))
        low, high = int(start[done]), int(end[stop - 1])
        up, down = _power(high - low + 1)
        total = np.zeros(high - low + 1, np.uint64)
        np.cumsum((buf[low:high].astype(np.uint64) + np.uint64(1)) * up[: high - low], out=total[1:])
        s, e = start[done:stop] - low, end[done:stop] - low
        out[done:stop] = (total[e] - total[s]) * down[s]
        done = stop
    return Words(buf, start, end, text, mix(out), first)


def ngrams(hashes: np.ndarray, n: int, salt: int = 0) -> np.ndarray:
    """Hash of every n consecutive words (len - n + 1 of them), across text borders too: mask with same_text."""
    count = max(0, len(hashes) - n + 1)
    out = np.full(count, np.uint64(n + salt * 1000003), np.uint64)
    for j in range(n):
        out = (out + hashes[j : j + count]) * _MULT
        out ^= out >> np.uint64(29)
    return mix(out)


def same_text(w: Words, n: int) -> np.ndarray:
    """True for the n-gram starts whose n words are of one text."""
    count = max(0, len(w.text) - n + 1)
    return w.text[:count] == w.text[n - 1 : n - 1 + count]


def word_hashes(sequence: list[bytes]) -> np.ndarray:
    """Hashes of single words, equal to those of words()."""
    buf = np.frombuffer(b"".join(sequence), np.uint8)
    offs = np.concatenate([[0], np.cumsum([len(x) for x in sequence])]).astype(np.int64)
    return words(buf, offs, np.ones(256, bool), lower=False).hash
