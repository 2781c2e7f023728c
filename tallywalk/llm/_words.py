"""Words, shingles and their hashes, shared by the operators on word shingles.

Words are hashed by array arithmetic over the code points of many texts at once: a word's hash is the sum of a factor for each character times one for its place,
mixed with its length. No word becomes an object of its own.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np

from tallywalk.llm._frame import in_parts

WIDTH = 5  # words of a shingle
LEAST = 0.8  # similarity of near copies
WORD = re.compile(r"\w+")
PART = 1 << 17  # characters that are hashed at once
MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)
MIX = np.uint64(0xBF58476D1CE4E5B9)
NO_HASH = np.zeros(0, np.uint64)


def words_of(text: str | None) -> list[str]:
    return WORD.findall(text.lower()) if text else []


def mixed(x: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = (x + np.uint64(1)) * MULTIPLIER
        x = (x ^ (x >> np.uint64(30))) * MIX
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


@lru_cache(maxsize=1)
def in_word() -> np.ndarray:
    """Whether a code point is part of a word, as WORD has it."""
    return np.fromiter((c == 95 or chr(c).isalnum() for c in range(0x110000)), bool, 0x110000)


@lru_cache(maxsize=1)
def low_factors() -> np.ndarray:
    return mixed(np.arange(1 << 16, dtype=np.uint64))


def factors(codes: np.ndarray) -> np.ndarray:
    low = low_factors()
    if codes.dtype == np.uint8 or not len(codes) or codes.max() < len(low):
        return low[codes]
    return mixed(codes.astype(np.uint64))


@lru_cache(maxsize=1)
def low_places() -> np.ndarray:
    return mixed(np.arange(1 << 32, (1 << 32) + 4096, dtype=np.uint64)) | np.uint64(1)


def places(at: np.ndarray) -> np.ndarray:
    low = low_places()
    if not len(at) or at.max() < len(low):
        return low[at]
    return mixed(at.astype(np.uint64) + np.uint64(1 << 32)) | np.uint64(1)


@lru_cache(maxsize=1)
def letters() -> np.ndarray:
    """Whether a code point is a letter: of the categories Lu, Ll, Lt, Lm, Lo."""
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)


def hash_runs(codes: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The hash of each run of code points, none empty; the runs follow each other."""
    if not len(lengths):
        return NO_HASH
    first = np.cumsum(lengths) - lengths
    with np.errstate(over="ignore"):
        each = factors(codes) * places(np.arange(len(codes)) - np.repeat(first, lengths))
        return mixed(np.add.reduceat(each, first) + lengths.astype(np.uint64))


def code_points(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """The texts in lower case as numbers, each followed by a line end, and where each ends."""
    lower = [t.lower() if t else "" for t in texts]
    joined = "\n".join([*lower, ""])
    ends = np.cumsum(np.fromiter(map(len, lower), np.int64, len(lower)) + 1)
    try:
        return np.frombuffer(joined.encode("latin-1"), np.uint8), ends
    except UnicodeEncodeError:
        return np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32), ends


def between_words(codes: np.ndarray, kind: np.ndarray) -> Iterator[tuple[int, int]]:
    """The code points in pieces of about 2 * PART that end between words (runs of a kind)."""
    a = 0
    while a < len(codes):
        b = min(len(codes), a + 2 * PART)
        while b < len(codes):
            gaps = np.flatnonzero(~kind[codes[b : b + PART]])
            if len(gaps):
                b += int(gaps[0])
                break
            b = min(len(codes), b + PART)
        yield a, b
        a = b


def runs_of(codes: np.ndarray, kind: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The code points of a kind, where each run of them begins, and how long it is."""
    inside = kind[codes]
    edges = np.flatnonzero(np.diff(inside, prepend=False, append=False))
    return codes[inside], edges[::2], edges[1::2] - edges[::2]


def hashed_words(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """The hashes of all words of the texts, and the number of words before each text and at the end."""
    codes, ends = code_points(texts)
    hashes, starts = [NO_HASH], [np.zeros(0, np.int64)]
    for a, b in between_words(codes, in_word()):
        inner, first, lengths = runs_of(codes[a:b], in_word())
        hashes.append(hash_runs(inner, lengths))
        starts.append(first + a)
    return np.concatenate(hashes), np.append(0, np.searchsorted(np.concatenate(starts), ends))


def shingles(hashes: np.ndarray, width: int = WIDTH) -> np.ndarray:
    """A hash for each run of `width` words; fewer words make one shingle, none make none."""
    n = len(hashes)
    if not n:
        return NO_HASH
    size = min(width, n)
    with np.errstate(over="ignore"):
        out = np.full(n - size + 1, size, np.uint64)
        for i in range(size):
            out = (out ^ hashes[i : n - size + 1 + i]) * MULTIPLIER
            out ^= out >> np.uint64(29)
        out *= MIX
        out ^= out >> np.uint64(32)
    return out


def shingled(texts: list[str | None]) -> Iterator[tuple[int, np.ndarray]]:
    """For each text its number of words and its shingles in order."""
    for some in in_parts(texts, PART):
        hashes, bounds = hashed_words(some)
        every = shingles(hashes)
        for a, b in zip(bounds.tolist(), bounds[1:].tolist()):
            yield b - a, every[a : b - WIDTH + 1] if b - a >= WIDTH else shingles(hashes[a:b])
