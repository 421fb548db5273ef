"""BPE encoding and decoding with a segment tree over adjacent pair ranks.

The leaves of the tree hold the merge rank of each adjacent pair of symbols, inner nodes the least of
their children; from the root one comes down to the leftmost pair of lowest rank. A merge changes three leaves, each
in logarithmic time, so a word of any length costs O(n log n); words of all lengths take this way. Words repeat, and so does what stands between
white space; each worker remembers the encoded form of short ones in bounded tables. New words of a group of texts are merged together: the trees of words of one width
are rows of one array, and each step takes the root of every tree.

Texts stay in their partition: one pass in Arrow batches, no shuffle, nothing kept between tasks.
"""

from __future__ import annotations

import hashlib
import json
import os
import unicodedata
from collections.abc import Callable, Iterable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from netjoin.llm.common import slices, text_or_empty

#: Bounds of a worker's two tables, of words and of runs between white space: entries of each of their two generations, and characters of what is remembered.
CACHE_ENTRIES, CACHE_CHARS = 180_000, 48

#: Most characters of texts whose new words are merged together (a longer text is alone), most leaves of trees that are, and most words.
GROUP_CHARS, WIDE, TOGETHER = 500_000, 64, 20_000

#: What ``str.split`` takes for white space and the ``\\s`` of patterns does not.
SEPARATORS = "\x1c\x1d\x1e\x1f"


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte, by the byte-level rule: printable Latin-1 stands for itself."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    table, extra = {b: chr(b) for b in own}, 256
    for b in range(256):
        if b not in table:
            table[b], extra = chr(extra), extra + 1
    return [table[b] for b in range(256)]


#: A pair's key is its rank above PLACE bits that hold where it stands, so that the least key is the leftmost pair of lowest rank.
NONE, PLACE = 1 << 62, 40


def climb(tree: list[int], i: int, value: int) -> None:
    """Set a leaf, and above it each node that changes."""
    while tree[i] != value:
        tree[i] = value
        if i == 1:
            return
        other = tree[i ^ 1]
        if other < value:
            value = other
        i >>= 1


def merge_symbols(symbols: list[int], ranks: dict[int, int], products: list[int]) -> list[int]:
    """Apply merges until none fits; lowest rank first, leftmost of equals. ``ranks``: first << 20 | second -> rank << PLACE; ``products``: the symbol each rank makes.

    The tree lies in one list: node i has the children 2i and 2i + 1, the leaves are the keys of the pairs, every node is the least of its children.
    """
    n = len(symbols)
    if n < 2:
        return symbols
    get = ranks.get
    width = 1 << (n - 2).bit_length() if n > 2 else 1
    keys = [get(a << 20 | b, NONE) for a, b in zip(symbols, symbols[1:])]
    tree = [NONE] * width + [k + i if k != NONE else k for i, k in enumerate(keys)] + [NONE] * (width - n + 1)
    for i in range(width - 1, 0, -1):
        a, b = tree[2 * i], tree[2 * i + 1]
        tree[i] = a if a < b else b
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    while (best := tree[1]) != NONE:
        at, merged = best & (1 << PLACE) - 1, products[best >> PLACE]
        gone = after[at]
        following = after[at] = after[gone]
        first = before[at]
        symbols[at], symbols[gone] = merged, -1
        if following < n:
            before[following] = at
            climb(tree, gone + width, NONE)
            key = get(merged << 20 | symbols[following])
            climb(tree, at + width, NONE if key is None else key + at)
        else:
            climb(tree, at + width, NONE)
        if first >= 0:
            key = get(symbols[first] << 20 | merged)
            climb(tree, first + width, NONE if key is None else key + first)
    return [s for s in symbols if s >= 0]


class Pairs:
    """The ranks of pairs as sorted arrays, to look many up at once."""

    def __init__(self, ranks: dict[int, int]):
        self.pairs = np.array([*sorted(ranks), NONE], np.int64)
        self.keys = np.array([*(ranks[p] for p in sorted(ranks)), NONE], np.int64)

    def keys_of(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        pair = a << 20 | b
        at = np.searchsorted(self.pairs, pair)
        return np.where(self.pairs[at] == pair, self.keys[at], NONE)


def merge_together(symbols: np.ndarray, sizes: np.ndarray, pairs: Pairs, products: np.ndarray) -> None:
    """``merge_symbols`` on every row at once, in place: rows hold ``sizes`` symbols of one more column than their trees have leaves; -1 marks what a merge took."""
    many, wide = symbols.shape
    width, step = wide - 1, 2 * wide - 2
    column = np.arange(width)
    keys = pairs.keys_of(symbols[:, :-1], symbols[:, 1:])
    tree = np.full((many, step), NONE, np.int64)
    tree[:, width:] = np.where((column < sizes[:, None] - 1) & (keys != NONE), keys + column, NONE)
    low = width
    while low > 1:
        tree[:, low >> 1 : low] = np.minimum(tree[:, low : 2 * low : 2], tree[:, low + 1 : 2 * low : 2])
        low >>= 1
    after, before = (np.tile(np.arange(first, first + wide), many) for first in (1, -1))
    symbols, tree, row = symbols.reshape(-1), tree.reshape(-1), np.arange(many)
    while True:
        best = tree[row * step + 1]
        fits = best != NONE
        row, best = row[fits], best[fits]
        if not len(row):
            return
        cells, leaves = row * wide, row * step + width
        at, merged = best & (1 << PLACE) - 1, products[best >> PLACE]
        gone = after[cells + at]
        following, first = after[cells + gone], before[cells + at]
        after[cells + at] = following
        symbols[cells + at], symbols[cells + gone] = merged, -1
        right, left = following < sizes[row], first >= 0
        before[(cells + following)[right]] = at[right]
        tree[leaves + at] = NONE
        tree[(leaves + gone)[right]] = NONE
        for some, one, a, b in ((right, at, merged, None), (left, first, None, merged)):
            place = one[some]
            a = symbols[(cells + first)[some]] if a is None else a[some]
            b = symbols[(cells + following)[some]] if b is None else b[some]
            key = pairs.keys_of(a, b)
            tree[leaves[some] + place] = np.where(key != NONE, key + place, NONE)
        root = np.concatenate([row, row[right], row[left]]) * step
        node = width + np.concatenate([at, gone[right], first[left]])
        for _ in range(width.bit_length() - 1):
            node >>= 1
            under = root + 2 * node
            tree[root + node] = np.minimum(tree[under], tree[under + 1])


class Remembered(dict):
    """Short keys with what ``make`` gives for them. A full table becomes the older one; keys met there again move back."""

    def __init__(self, make: Callable[[str], tuple[str, str]]):
        super().__init__()
        self.make, self.older = make, {}

    def __missing__(self, key: str) -> tuple[str, str]:
        return self.add(key, self.older.get(key) or self.make(key))

    def add(self, key: str, out: tuple[str, str]) -> tuple[str, str]:
        if len(key) <= CACHE_CHARS:
            if len(self) >= CACHE_ENTRIES:
                self.older = dict(self)
                self.clear()
            self[key] = out
        return out


def joined(encoded: list[tuple[str, str]]) -> tuple[str, str]:
    """Ids and tokens of what follows one another."""
    return (" ".join([e[0] for e in encoded]), " ".join([e[1] for e in encoded])) if len(encoded) != 1 else encoded[0]


class WordTokenizer:
    """Encoder and decoder for a tokenizer file of BPE with byte symbols and word ends.

    Follows the file: its special tokens are cut out of the raw text first, then each piece is put in NFC,
    letters become lower case one by one, the split pattern yields words, and merges apply in each word. The pattern never matches white space (a file whose
    pattern does is refused), so words are looked for in each run between white space.
    Decoding joins the tokens by one space, as the library does for a file without a decoder.
    """

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        vocab = model["vocab"]
        self.end = model["end_of_word_suffix"] or ""
        self.specials = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.tokens = {i: t for t, i in vocab.items()} | {i: t for t, i in self.specials.items()}
        pairs = [pair.split(" ") if isinstance(pair, str) else pair for pair in model["merges"]]
        self.products = [vocab[a + b] for a, b in pairs]
        self.ranks: dict[int, int] = {}
        for rank, (a, b) in enumerate(pairs):
            self.ranks.setdefault(vocab[a] << 20 | vocab[b], rank << PLACE)
        self.pairs, self.made = Pairs(self.ranks), np.array(self.products, np.int64)
        symbols = byte_symbols()
        self.inner, self.last = [vocab[s] for s in symbols], [vocab[s + self.end] for s in symbols]
        self.words = regex.compile(next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split"))
        self.inner_of, self.last_of, self.digits = np.array(self.inner), np.array(self.last), {i: str(i) for i in self.tokens}
        self.cut = regex.compile("|".join(regex.escape(s) for s in self.specials)) if self.specials else None
        self.lead = os.path.commonprefix(list(self.specials))
        if self.words.search(" "):
            raise ValueError("a split pattern that matches white space is not supported")
        self.run = regex.compile(r"\S+")
        self.known_words, self.known_runs = Remembered(self._encode_word), Remembered(self._encode_run)

    def word_ids(self, word: str) -> list[int]:
        raw = word.encode("utf-8", "surrogatepass")
        inner = self.inner
        return merge_symbols([inner[b] for b in raw[:-1]] + [self.last[raw[-1]]], self.ranks, self.products)

    def _encode_word(self, word: str) -> tuple[str, str]:
        """Ids and tokens, each joined by spaces."""
        ids = self.word_ids(word)
        return " ".join(map(str, ids)), " ".join([self.tokens[i] for i in ids])

    def _encode_words(self, words: list[str]) -> Iterator[tuple[str, tuple[str, str]]]:
        """Words with their ids and tokens; those whose trees are of one width are merged together."""
        raw = [word.encode("utf-8", "surrogatepass") for word in words]
        sizes = np.fromiter(map(len, raw), np.int64, len(raw))
        width = np.where(sizes > 2, 1 << np.ceil(np.log2(np.maximum(sizes - 1, 1))).astype(np.int64), 1)
        for i in np.flatnonzero((sizes < 2) | (width > WIDE)).tolist():
            yield words[i], self._encode_word(words[i])
        for wide in np.unique(width[(sizes > 1) & (width <= WIDE)]).tolist():
            every = np.flatnonzero((sizes > 1) & (width == wide))
            for begin in range(0, len(every), TOGETHER):
                some = every[begin : begin + TOGETHER]
                n, names = sizes[some], some.tolist()
                used, symbols = np.arange(wide + 1) < n[:, None], np.zeros((len(some), wide + 1), np.int64)
                letters = np.frombuffer(b"".join([raw[i] for i in names]), np.uint8)
                symbols[used] = self.inner_of[letters]
                symbols[np.arange(len(n)), n - 1] = self.last_of[letters[np.cumsum(n) - 1]]
                merge_together(symbols, n, self.pairs, self.made)
                used &= symbols >= 0
                ids, ends = symbols[used].tolist(), np.cumsum(used.sum(axis=1)).tolist()
                digits, tokens = [self.digits[i] for i in ids], [self.tokens[i] for i in ids]
                for i, at, end in zip(names, [0, *ends], ends):
                    yield words[i], (" ".join(digits[at:end]), " ".join(tokens[at:end]))

    def _encode_run(self, run: str) -> tuple[str, str]:
        """Ids and tokens of a run without white space, each joined by spaces."""
        return joined([self.known_words[word] for word in self.words.findall(run)])

    def runs(self, piece: str) -> list[str]:
        """Normalised text between white space."""
        if not piece.isascii():
            piece = unicodedata.normalize("NFC", piece).replace("Σ", "σ")
        piece = piece.lower()
        return self.run.findall(piece) if any(c in piece for c in SEPARATORS) else piece.split()

    def _pieces(self, text: str) -> Iterator[tuple[str, str]]:
        at = 0
        for m in self.cut.finditer(text) if self.cut and self.lead in text else ():
            yield text[at : m.start()], m[0]
            at = m.end()
        yield text[at:], ""

    def _cut(self, text: str) -> list[tuple[list[str], str]]:
        return [(self.runs(piece), special) for piece, special in self._pieces(text)]

    def _of_parts(self, parts: list[tuple[list[str], str]], known: dict[str, tuple[str, str]]) -> tuple[str, str]:
        hits = []
        for runs, special in parts:
            hits += map(known.__getitem__, runs)
            if special:
                hits.append((str(self.specials[special]), special))
        return joined(hits)

    def encoded(self, text: str) -> tuple[str, str]:
        """Decimal ids joined by one space, and the decoded text."""
        return self._of_parts(self._cut(text), self.known_runs)

    def encoded_all(self, texts: Iterable[str]) -> Iterator[tuple[str, str]]:
        """``encoded`` of each text; what is new in some of them is encoded together."""
        group, size = [], 0
        for text in texts:
            if group and size + len(text) > GROUP_CHARS:
                yield from self._encoded_group(group)
                group, size = [], 0
            group.append(text)
            size += len(text)
        yield from self._encoded_group(group)

    def _encoded_group(self, texts: list[str]) -> Iterator[tuple[str, str]]:
        cut = [self._cut(text) for text in texts]
        runs, own = set(chain.from_iterable([part for parts in cut for part, _ in parts])), self.known_runs
        known = {run: own[run] for run in runs if run in own or run in own.older}
        new = {run: self.words.findall(run) for run in runs if run not in known}
        words, own = set(chain.from_iterable(new.values())), self.known_words
        found = {word: own[word] for word in words if word in own or word in own.older}
        for word, out in self._encode_words([word for word in words if word not in found]):
            found[word] = own.add(word, out)
        for run, words in new.items():
            known[run] = self.known_runs.add(run, found[words[0]] if len(words) == 1 else joined([found[word] for word in words]))
        for parts in cut:
            yield self._of_parts(parts, known)

    def encode(self, text: str) -> list[int]:
        joined = self.encoded(text)[0]
        return [int(i) for i in joined.split(" ")] if joined else []

    def decode(self, ids: list[int]) -> str:
        return " ".join([self.tokens[i] for i in ids])


_LOADED: dict[str, WordTokenizer] = {}


def tokenizer(path: str) -> WordTokenizer:
    """The tokenizer of a path, loaded once in each Python worker."""
    if path not in _LOADED:
        _LOADED[path] = WordTokenizer(path)
    return _LOADED[path]


def bpe_digests(docs: DataFrame, path: str, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 for every row.

    Null and empty texts have no tokens and the digests of the empty string. Texts of any length are encoded whole. Equal ranks merge from the left.
    Rows that repeat are encoded each, a null id is passed on, an empty table gives no rows, and other columns of ``docs`` are not read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = tokenizer(path)
        for batch in slices(batches):
            n, a, b = [], [], []
            for ids, decoded in t.encoded_all(batch.column(1).to_pylist()):
                n.append(ids.count(" ") + 1 if ids else 0)
                a.append(hashlib.sha256(ids.encode()).hexdigest())
                b.append(hashlib.sha256(decoded.encode("utf-8", "surrogatepass")).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def bpe_encode(docs: DataFrame, path: str, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, token_ids array<int>, n_tokens for every row; the same cases as in ``bpe_digests``, with an empty list where there are no tokens."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = tokenizer(path)
        for batch in slices(batches):
            lists, ends = [], [0]
            for joined, _ in t.encoded_all(batch.column(1).to_pylist()):
                lists.append(np.fromstring(joined, dtype=np.int32, sep=" ") if joined else np.empty(0, np.int32))
                ends.append(ends[-1] + len(lists[-1]))
            ids = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(lists) if lists else np.empty(0, np.int32), pa.int32()))
            yield pa.RecordBatch.from_arrays([batch.column(0), ids, pa.array(np.diff(ends), pa.int64())], names=["doc_id", "token_ids", "n_tokens"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"doc_id {kind}, token_ids array<int>, n_tokens long")


def bpe_decode(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id, text from doc_id, token_ids; null lists decode to the empty text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = tokenizer(path)
        for batch in slices(batches):
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([t.decode(ids or []) for ids in batch.column(1).to_pylist()], pa.string())], names=["doc_id", "text"])

    kind = encoded.schema["doc_id"].dataType.simpleString()
    return encoded.select("doc_id", "token_ids").mapInArrow(run, f"doc_id {kind}, text string")
