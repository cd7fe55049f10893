"""Exact word-wise use of a whitespace-splitting tokenizer file.

The tokenizer drops white space, and none of its steps looks across it, so the ids of a
text are the ids of its white-space words in a row. Words repeat far more than texts do,
so each Python worker keeps a bounded dictionary from pre-token to ids and gives the
library's model only pre-tokens it has not met. Texts for which the claim could fail (added-token strings,
control characters on which Python and the tokenizer differ about white space) go to the
library whole.
"""

from __future__ import annotations

import gc
import re
import sys
from bisect import bisect_right

import numpy as np

#: Pre-tokens or words kept by a worker before its dictionary is emptied (bounds memory; results do not depend on it).
MAX_WORDS = 600_000
#: Python splits at U+001C..U+001F, the tokenizer does not; "<|" starts the added tokens.
ODD = re.compile("[\x1c-\x1f]|<\\|")


def per_worker(key: tuple, make):
    """What make() gives, kept for later tasks of this Python worker.

    Functions reach workers by value, with globals of their own, so the store hangs on sys.
    """
    gc.set_threshold(500_000, 20, 20)  # the dictionaries are no garbage; walking them is dear
    kept = sys.__dict__.setdefault("_veilstream_kept", {})
    if key not in kept:
        kept[key] = make()
    return kept[key]


def end_of_task() -> None:
    """Give what this worker keeps back to the machine: idle workers stay while other stages run."""
    import ctypes

    import pyarrow

    sys.__dict__.pop("_veilstream_kept", None)
    gc.collect()
    pyarrow.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def load_tokenizer(path: str):
    from tokenizers import Tokenizer

    return per_worker(("tokenizer", path), lambda: Tokenizer.from_file(path))


def word_encoder(path: str, most: int = MAX_WORDS) -> WordEncoder:
    return per_worker(("encoder", path, most), lambda: WordEncoder(path, most))


def merge_counter(path: str) -> MergeCounter:
    return per_worker(("counter", path), lambda: MergeCounter(path))


#: Fixed value: the split pattern for which printable ASCII words may be split here.
WORD_END_PATTERN = "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+"
#: Texts of these characters are in normal form C and split by PIECES, once lower-cased, just as by the pattern above.
PLAIN = re.compile("[\\t\\n\\r -~À-ÖØ-öø-į]*")
PIECES = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-į]+|[0-9]|[^\\sa-z0-9ß-öø-į]+")


class WordPieces:
    """Splits texts into the pre-tokens that the tokenizer's model gets."""

    def __init__(self, tok):
        import json

        spec = json.loads(tok.to_str())
        splits = (spec["pre_tokenizer"] or {}).get("pretokenizers") or []
        lowers = any(n["type"] == "Lowercase" for n in (spec["normalizer"] or {}).get("normalizers") or [])
        self.tok = tok
        self.known_pattern = lowers and [x["type"] for x in splits] == ["Split", "ByteLevel"] and splits[0]["pattern"] == {"Regex": WORD_END_PATTERN}

    def plain(self, text: str) -> bool:
        """Whether PIECES splits this text's words as the library does."""
        return self.known_pattern and PLAIN.fullmatch(text) is not None and "<|" not in text

    def mapped(self, piece: str) -> str:
        return piece if piece.isascii() else "".join(p for p, _ in self.tok.pre_tokenizer.pre_tokenize_str(piece))

    def split(self, words: list[str]) -> list[list[str]]:
        """Mapped pre-tokens of white-space words, by the library."""
        out: list[list[str]] = [[] for _ in words]
        for k in range(0, len(words), 4096):
            plain = self.tok.normalizer.normalize_str(" ".join(words[k : k + 4096]))
            starts = [0]
            for w in plain.split(" ")[:-1]:
                starts.append(starts[-1] + len(w) + 1)
            for p, (a, _) in self.tok.pre_tokenizer.pre_tokenize_str(plain):
                out[k + bisect_right(starts, a) - 1].append(p)
        return out


class PieceCache(dict):
    """Piece -> what make(piece) gives; emptied when it holds `most`."""

    def __init__(self, make, most: int = MAX_WORDS):
        super().__init__()
        self.make, self.most = make, most

    def __missing__(self, piece: str):
        if len(self) >= self.most:
            self.clear()
        out = self[piece] = self.make(piece)
        return out


class WordEncoder:
    """raw(text) -> ids, equal to the library's without special tokens added."""

    def __init__(self, path: str, most: int = MAX_WORDS):
        self.tok = load_tokenizer(path)
        self.pieces = WordPieces(self.tok)
        model, mapped = self.tok.model.tokenize, self.pieces.mapped
        ids = lambda p: b"".join([t.id.to_bytes(4, "little") for t in model(p)])

        def plain(word: str) -> bytes:
            pieces = PIECES.findall(word.lower())  # a pre-token is a word of which it is the only one
            return ids(mapped(word)) if pieces == [word] else b"".join([self.of_plain[p] for p in pieces])

        self.of_plain = PieceCache(plain, most)
        self.of_word = PieceCache(lambda w: b"".join(map(ids, self.pieces.split([w])[0])), most)

    def raw(self, text: str | None) -> bytes:
        """The ids as little-endian unsigned 32-bit integers."""
        if not text:
            return b""
        if self.pieces.plain(text):
            return b"".join(map(self.of_plain.__getitem__, text.split()))
        if ODD.search(text):
            return np.asarray(self.tok.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()
        return b"".join(map(self.of_word.__getitem__, text.split()))


class MergeCounter:
    """count(text) -> number of tokens, by counting merges; no ids are made.

    Each pre-token is a doubly linked list of symbols with a heap of adjacent pairs keyed by
    (merge rank, place); popping the lowest pair joins two symbols and puts the two new
    neighbouring pairs on the heap. Stale heap entries are known by their changed symbols.
    Tokens = initial symbols - merges.
    """

    def __init__(self, path: str):
        import json

        self.tok = load_tokenizer(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        vocab = model["vocab"]
        self.suffix = model.get("end_of_word_suffix") or ""
        self.ranks: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, pair in enumerate(model["merges"]):
            a, b = pair.split(" ") if isinstance(pair, str) else pair
            self.ranks[(vocab[a], vocab[b])] = (rank, vocab[a + b])
        self.symbol = {s: i for s, i in vocab.items() if len(s.removesuffix(self.suffix)) <= 1 or len(s) == 1}
        self.added = [t["content"] for t in spec["added_tokens"]]
        self.cut = re.compile("|".join(map(re.escape, self.added))) if self.added else None
        self.pieces = WordPieces(self.tok)

        def plain(word: str) -> int:
            pieces = PIECES.findall(word.lower())
            return self.merged(self.pieces.mapped(word)) if pieces == [word] else sum([self.of_plain[p] for p in pieces])

        self.of_plain = PieceCache(plain)
        self.of_word = PieceCache(lambda w: sum(map(self.merged, self.pieces.split([w])[0])))

    def merged(self, piece: str) -> int:
        from heapq import heapify, heappop, heappush

        sym = [self.symbol[c] for c in piece[:-1] if c in self.symbol]
        last = self.symbol.get(piece[-1] + self.suffix)
        if last is not None:
            sym.append(last)
        n = len(sym)
        ranks, prev, nxt = self.ranks, list(range(-1, n - 1)), [*range(1, n), -1]
        heap = [(r[0], i, sym[i], sym[i + 1], r[1]) for i in range(n - 1) if (r := ranks.get((sym[i], sym[i + 1])))]
        heapify(heap)
        merges = 0
        while heap:
            _, i, a, b, ab = heappop(heap)
            j = nxt[i]
            if sym[i] != a or j < 0 or sym[j] != b:
                continue
            sym[i], sym[j] = ab, -1
            merges += 1
            k = nxt[j]
            nxt[i] = k
            if k >= 0:
                prev[k] = i
                if r := ranks.get((ab, sym[k])):
                    heappush(heap, (r[0], i, ab, sym[k], r[1]))
            h = prev[i]
            if h >= 0 and (r := ranks.get((sym[h], ab))):
                heappush(heap, (r[0], h, sym[h], ab, r[1]))
        return n - merges

    def split_count(self, text: str) -> int:
        """A text without added tokens, without the word dictionary."""
        if not text:
            return 0
        return sum(self.merged(p) for p, _ in self.tok.pre_tokenizer.pre_tokenize_str(self.tok.normalizer.normalize_str(text)))

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if self.pieces.plain(text):
            return sum(map(self.of_plain.__getitem__, text.split()))
        if ODD.search(text):
            parts = self.cut.split(text) if self.cut else [text]
            return len(parts) - 1 + sum(map(self.split_count, parts))
        return sum(map(self.of_word.__getitem__, text.split()))
