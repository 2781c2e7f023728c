"""BPE encoding and decoding with a segment tree over the ranks of adjacent pairs.

The leaves of the tree are the adjacent pairs of a word, in order; a leaf holds rank and position in one
number, and an inner node the smaller of its children, so that the root is the leftmost pair of the lowest rank.
A merge changes three leaves at most, each in O(log n), until the root says that no pair can merge: a word of
n symbols takes O(n log n), whatever its length.

Texts are cut into words first by the vocabulary's own rule. Words repeat, so their results are held in a table of
bounded size, and words of like lengths are merged side by side, one level of all their trees at a time.

Defined results: a null or empty text has no ids, decoded text "". Repeated rows give repeated results. Other
columns, whatever their names, are not read; text of any length is encoded whole.
"""

from __future__ import annotations

import hashlib
import itertools
import json
import re
import sys
import unicodedata
from functools import lru_cache

import numpy as np
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallywalk.llm._frame import Memo, alone, in_parts, struct_udf, unclashing

NO_PAIR = 1 << 62


def merge_word(symbols: list[int], pairs: dict[tuple[int, int], tuple[int, int]]) -> list[int]:
    """The symbols after all merges. pairs: (left, right) to (rank, merged symbol)."""
    n = len(symbols)
    if n < 2:
        return symbols
    width = 1
    while width < n - 1:
        width *= 2
    got = [pairs.get(p) for p in zip(symbols, symbols[1:])]
    tree = [NO_PAIR] * (2 * width)
    tree[width : width + n - 1] = [NO_PAIR if g is None else g[0] * n + i for i, g in enumerate(got)]
    for i in range(width - 1, 0, -1):
        a, b = tree[2 * i], tree[2 * i + 1]
        tree[i] = a if a < b else b
    if tree[1] == NO_PAIR:
        return symbols
    symbols, after, before = list(symbols), list(range(1, n + 1)), list(range(-1, n - 1))

    def put(leaf: int, value: int) -> None:
        i = width + leaf
        tree[i] = value
        while i > 1:
            i >>= 1
            a, b = tree[2 * i], tree[2 * i + 1]
            if b < a:
                a = b
            if tree[i] == a:
                return
            tree[i] = a

    def pair_at(i: int) -> int:
        j = after[i]
        g = pairs.get((symbols[i], symbols[j])) if j < n else None
        return NO_PAIR if g is None else g[0] * n + i

    while tree[1] != NO_PAIR:
        i = tree[1] % n
        j = after[i]
        symbols[i] = pairs[symbols[i], symbols[j]][1]
        after[i] = k = after[j]
        symbols[j] = -1
        if k < n:
            before[k] = i
        if j < n - 1:
            put(j, NO_PAIR)
        if i < n - 1:
            put(i, pair_at(i))
        if before[i] >= 0:
            put(before[i], pair_at(before[i]))
    return [s for s in symbols if s >= 0]


class PairTable:
    """The merges as sorted arrays, for many words at once."""

    def __init__(self, pairs: dict[tuple[int, int], tuple[int, int]]):
        keys = np.array([a << 32 | b for a, b in pairs], dtype=np.int64)
        ranks = np.array([r for r, _ in pairs.values()], dtype=np.int64)
        order = np.argsort(keys)
        self.keys, self.ranks = np.append(keys[order], NO_PAIR), np.append(ranks[order], 0)
        self.merged = np.zeros(int(ranks.max(initial=0)) + 1, dtype=np.int64)
        self.merged[ranks] = [m for _, m in pairs.values()]

    def leaves(self, left: np.ndarray, right: np.ndarray, at: np.ndarray, shift: int) -> np.ndarray:
        """Rank and position of pairs; a symbol below 0 stands for none."""
        keys = left << 32 | right
        k = np.searchsorted(self.keys, keys)
        return np.where((self.keys[k] == keys) & (left >= 0) & (right >= 0), self.ranks[k] << shift | at, NO_PAIR)


def merge_words(words: list[list[int]], width: int, table: PairTable) -> list[tuple[int, ...]]:
    """merge_word for words of at most width + 1 symbols (a power of two and one), a merge of each word in every turn."""
    w, shift, cols = len(words), width.bit_length(), width + 2
    counts = np.fromiter(map(len, words), np.int64, w)
    symbols = np.full((w, cols), -1, dtype=np.int64)
    symbols[np.arange(cols) < counts[:, None]] = np.fromiter(itertools.chain.from_iterable(words), np.int64, int(counts.sum()))
    tree = np.full((w, 2 * width), NO_PAIR, dtype=np.int64)
    tree[:, width:] = table.leaves(symbols[:, :width], symbols[:, 1 : width + 1], np.arange(width), shift)
    for i in range(width - 1, 0, -1):
        np.minimum(tree[:, 2 * i], tree[:, 2 * i + 1], out=tree[:, i])
    after = np.tile(np.arange(1, cols + 1), (w, 1))
    before = np.tile(np.arange(-1, cols - 1), (w, 1))
    tree_f, symbols_f, after_f, before_f = tree.ravel(), symbols.ravel(), after.ravel(), before.ravel()
    rows = np.flatnonzero(tree[:, 1] != NO_PAIR)
    while len(rows):
        at, top = rows * cols, rows * 2 * width
        root = tree_f[top + 1]
        i = root & ((1 << shift) - 1)
        j = after_f[at + i]
        k = np.minimum(after_f[at + j], width + 1)
        p = before_f[at + i]
        symbols_f[at + i] = new = table.merged[root >> shift]
        symbols_f[at + j] = -1
        after_f[at + i] = k
        before_f[at + k] = i
        first = np.where(p >= 0, symbols_f[at + np.maximum(p, 0)], -1)
        leaf_i, leaf_p, leaf_j = width + i, np.where(p >= 0, width + p, 0), np.where(j < width, width + j, 0)
        tree_f[top + leaf_i] = table.leaves(new, symbols_f[at + k], i, shift)
        tree_f[top + leaf_p] = table.leaves(first, new, np.maximum(p, 0), shift)
        tree_f[top + leaf_j] = NO_PAIR
        for _ in range(width.bit_length() - 1):
            for leaf in (leaf_i, leaf_p, leaf_j):
                leaf >>= 1
                below = top + 2 * leaf
                tree_f[top + leaf] = np.minimum(tree_f[below], tree_f[below + 1])
        rows = rows[tree_f[top + 1] != NO_PAIR]
    keep = symbols >= 0
    flat, ends = symbols[keep].tolist(), np.cumsum(keep.sum(axis=1)).tolist()
    return [tuple(flat[a:b]) for a, b in zip([0, *ends], ends)]


def byte_letters() -> list[str]:
    """The printable character that stands for each byte in a byte-level vocabulary: itself where printable, else the next from U+0100."""
    own = {b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b}
    spare = itertools.count(256)
    return [chr(b) if b in own else chr(next(spare)) for b in range(256)]


class WordBpe:
    """A codec for a vocabulary file of the kind "BPE with word ends": lower case, white space dropped, byte-level letters."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab, self.end = spec["model"]["vocab"], spec["model"]["end_of_word_suffix"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.tokens = {i: t for t, i in itertools.chain(vocab.items(), self.special.items())}
        self.pairs = {}
        for rank, pair in enumerate(spec["model"]["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            self.pairs[vocab[a], vocab[b]] = rank, vocab[a + b]
        self.table = PairTable(self.pairs)
        letters = byte_letters()
        self.inner = [vocab[c] for c in letters]
        self.last = [vocab[c + self.end] for c in letters]
        self.path, self.byte_of = path, {c: b for b, c in enumerate(letters)}
        split = next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.pieces = regex.compile(split)
        self.cut = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        self.words = Memo(1 << 16)

    def split(self, text: str | None) -> list[str | int]:
        """The words of a text, and its special tokens as their ids."""
        if not text:
            return []
        if self.cut and any(s in text for s in self.special):
            parts = [x for x in self.cut.split(text) if x]
            return [y for x in parts for y in ([self.special[x]] if x in self.special else self.split(x))]
        if not is_latin(text):
            if newer_characters().search(text):
                return self.split_by_library(text)
            text = unicodedata.normalize("NFC", text).replace("Σ", "σ")  # letter by letter: no final sigma
        return self.pieces.findall(text.lower())

    def split_by_library(self, text: str) -> list[str]:
        """For characters newer than Python's Unicode tables: the vocabulary's library knows their case and kind."""
        own = library(self.path)
        pieces = own.pre_tokenizer.pre_tokenize_str(own.normalizer.normalize_str(text))
        return [bytes(self.byte_of[c] for c in p).decode() for p, _ in pieces]

    def encode_words(self, words: list[bytes]) -> list[tuple[int, ...]]:
        """Each word's ids: short words of like lengths together, the others one by one."""
        out: list = [None] * len(words)
        groups: dict[int, list[int]] = {}
        for i, word in enumerate(words):
            if len(word) < 2:
                out[i] = (self.last[word[0]],)
            else:
                groups.setdefault(max(2, 1 << (len(word) - 2).bit_length()), []).append(i)
        for width, those in groups.items():
            symbols = [[*map(self.inner.__getitem__, words[i][:-1]), self.last[words[i][-1]]] for i in those]
            if width > 64 or len(those) < 24:
                got = [tuple(merge_word(s, self.pairs)) for s in symbols]
            else:
                got = merge_words(symbols, width, self.table)
            for i, ids in zip(those, got):
                out[i] = ids
        return out

    def learn(self, lists: list[list[str | int]]) -> None:
        """From now until the next call self.words.now has every word of the lists: ids, ids in decimal, decoded."""
        new = self.words.make_room(set().union(*lists))
        plain = [w for w in new if isinstance(w, str)]
        for word, ids in itertools.chain(zip(plain, self.encode_words([w.encode() for w in plain])), ((w, (w,)) for w in new if isinstance(w, int))):
            self.words.now[word] = ids, " ".join(map(str, ids)), self.decode(ids)

    def over(self, texts: list[str | None], part: int = 1 << 19):
        """The values of the words of each text, learned a few million characters at a time."""
        for some in in_parts(texts, part):
            lists = list(map(self.split, some))
            self.learn(lists)
            for words in lists:
                yield list(map(self.words.now.__getitem__, words))

    def encode(self, text: str | None) -> list[int]:
        return self.encode_all([text])[0]

    def encode_all(self, texts: list[str | None]) -> list[list[int]]:
        return [[i for ids, _, _ in got for i in ids] for got in self.over(texts)]

    def decode(self, ids) -> str:
        return " ".join(map(self.tokens.__getitem__, ids))

    def digests(self, texts: list[str | None]) -> list[tuple[int, str, str]]:
        out = []
        for got in self.over(texts):
            ids = " ".join([x for _, x, _ in got])
            out.append((ids.count(" ") + bool(ids), hashlib.sha256(ids.encode()).hexdigest(), hashlib.sha256(" ".join([x for _, _, x in got]).encode()).hexdigest()))
        return out


def is_latin(text: str) -> bool:
    """Whether all characters are below U+0100, where normal forms and case are settled."""
    try:
        text.encode("latin-1")
    except UnicodeEncodeError:
        return False
    return True


@lru_cache(maxsize=1)
def newer_characters() -> re.Pattern:
    """Matches what Python's Unicode tables do not know."""
    spans: list[list[int]] = []
    for c in range(sys.maxunicode + 1):
        if unicodedata.category(chr(c)) == "Cn":
            if spans and spans[-1][1] == c - 1:
                spans[-1][1] = c
            else:
                spans.append([c, c])
    return re.compile("[" + "".join(f"\\U{a:08x}-\\U{b:08x}" for a, b in spans) + "]")


@lru_cache(maxsize=4)
def library(path: str):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


@alone
def codec(path: str) -> WordBpe:
    return WordBpe(path)


def encode(df: DataFrame, vocabulary: str, text: str = "text", ids: str = "ids") -> DataFrame:
    """df with the ids of each text as array<int>. vocabulary: a path that every executor can read."""

    def run(texts):
        return {"v": codec(vocabulary).encode_all(texts)}

    return df.withColumn(ids, struct_udf(run, "v array<int>")(F.col(text))["v"])


def decode(df: DataFrame, vocabulary: str, ids: str = "ids", text: str = "decoded") -> DataFrame:
    """df with the text of each array of ids; null counts as empty."""

    def run(rows):
        return {"v": [codec(vocabulary).decode(r or ()) for r in rows]}

    return df.withColumn(text, struct_udf(run, "v string")(F.col(ids))["v"])


def digest(df: DataFrame, vocabulary: str, keys: list[str], text: str = "text") -> DataFrame:
    """keys, n_tokens, and SHA-256 of the ids in decimal and of the decoded text, without moving either out of the worker. Keys of these names are replaced."""

    def run(texts):
        n, a, b = zip(*codec(vocabulary).digests(texts)) if texts else ((), (), ())
        return {"n_tokens": n, "ids_sha256": a, "decoded_sha256": b}

    made = struct_udf(run, "n_tokens bigint, ids_sha256 string, decoded_sha256 string")
    keys = unclashing(keys, "n_tokens", "ids_sha256", "decoded_sha256")
    return df.select(*keys, made(F.col(text)).alias("__made")).select(*keys, "__made.*")
