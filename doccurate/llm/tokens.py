"""Exact token ids and counts of public tokenizers with whole-token shortcuts.

A text is cut at white space where the tokenizer's pre-tokens must end, so every chunk can be
encoded alone. Chunks are memoised per Python worker (bounded), and pre-tokens that the
vocabulary holds as one token are never merged.
"""

from __future__ import annotations

import json
import re
from functools import lru_cache

import numpy as np

#: Chunks longer than this are encoded but not memoised; a memo is emptied beyond MEMO entries.
LONGEST_MEMO, MEMO, LONGEST_MERGE = 64, 400_000, 40
_ODD_SPACE = re.compile(r"\s (?:\s|\Z)")
_CUT = re.compile(r"(?<=\S)(?= \S)")
#: Pre-token patterns of the two vocabularies (fixed values, as the files and their README give them), for plain chunks.
_WORD_PRE = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\w\s]|_)+")
_BYTE_PRE = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?[^\W\d_]+| ?\d+| ?(?:[^\w\s]|_)+|\s+(?!\S)|\s+")
#: Chunks in which the patterns above and the libraries' agree: ASCII and the letters of Latin-1.
_PLAIN = re.compile(r"[ \n\x21-\x7eÀ-ÖØ-öø-ÿ]+\Z")
#: Words with characters beyond the plain ones.
_ODD_WORD = re.compile(r"([^ \n]*[^ \n\x21-\x7eÀ-ÖØ-öø-ÿ][^ \n]*)")


def single_token_strings(path: str) -> dict[str, int]:
    """Vocabulary strings proven to encode alone as the one token they name.

    A BPE vocabulary string is rebuilt by its own merges unless an earlier merge takes a letter
    away from it, so each candidate is encoded once by the library and kept only if the result is
    that one id. Byte-level strings that aren't whole UTF-8, and special tokens, are left out.
    """
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    with open(path, encoding="utf-8") as f:
        model = json.load(f)["model"]
    end, byte_of = model["end_of_word_suffix"] or "", _byte_alphabet()
    names, ids = [], []
    for token, number in model["vocab"].items():
        if end and not token.endswith(end):
            continue
        try:
            names.append(bytes(byte_of[c] for c in token.removesuffix(end)).decode())
            ids.append(number)
        except (KeyError, UnicodeDecodeError):
            continue
    found = tokenizer.encode_batch(names, add_special_tokens=False)
    return {name: i for name, i, e in zip(names, ids, found, strict=True) if name and e.ids == [i]}


def _byte_alphabet() -> dict[str, int]:
    """Characters of byte-level vocabularies: printable bytes stand for themselves, the rest follow from U+0100."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


class Merger:
    """Byte-pair merges of many short pre-tokens at once: each step joins the leftmost pair of lowest rank of every row."""

    def __init__(self, model: dict):
        vocab, end = model["vocab"], model["end_of_word_suffix"] or ""
        byte_of = _byte_alphabet()
        self.first, self.last = np.full(256, -1), np.full(256, -1)
        for c, b in byte_of.items():
            self.first[b], self.last[b] = vocab.get(c, -1), vocab.get(c + end, -1)
        pairs = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        keys = np.array([vocab[a] << 20 | vocab[b] for a, b in pairs], np.int64)
        self.made = np.array([vocab[a + b] for a, b in pairs] + [-1], np.int64)
        self.none = len(pairs)
        # Open addressing: at most STEPS places have to be looked at.
        self.mask = (1 << 19) - 1
        self.keys, self.ranks = np.full(self.mask + 1, -1, np.int64), np.full(self.mask + 1, self.none, np.int64)
        left, self.steps = np.arange(len(keys)), 0
        while len(left):
            at = (self._home(keys[left]) + self.steps) & self.mask
            free = self.keys[at] < 0
            _, one = np.unique(at[free], return_index=True)
            won = np.flatnonzero(free)[one]
            self.keys[at[won]], self.ranks[at[won]] = keys[left[won]], left[won]
            left = np.delete(left, won)
            self.steps += 1

    @staticmethod
    def _home(keys: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return (keys * np.int64(0x2545F4914F6CDD1D)) >> 45 & ((1 << 19) - 1)

    def rank(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        keys = a << 20 | b
        home, out = self._home(keys), np.full(keys.shape, self.none, np.int64)
        for k in range(self.steps):
            at = (home + k) & self.mask
            hit = self.keys[at] == keys
            out[hit] = self.ranks[at[hit]]
            if k == 0:
                odd = ~hit & (self.keys[at] >= 0)
                if not odd.any():
                    break
        out[(a < 0) | (b < 0)] = self.none
        return out

    def __call__(self, words: list[bytes], ended: bool = True) -> list[np.ndarray]:
        """Ids of each pre-token (not empty, not long); ended: its last byte closes a word."""
        lengths = np.array([len(w) for w in words], np.int64)
        out: list[np.ndarray] = [None] * len(words)  # type: ignore[list-item]
        order = np.argsort(lengths, kind="stable")
        for lo in range(0, len(words), 4096):
            rows = order[lo : lo + 4096]
            n, size = len(rows), lengths[rows]
            flat = np.frombuffer(b"".join(words[i] for i in rows.tolist()), np.uint8)
            ids = np.full((n, int(size.max())), -1, np.int64)
            where = np.arange(ids.shape[1])[None] < size[:, None]
            ids[where] = self.first[flat]
            ids[np.arange(n), size - 1] = (self.last if ended else self.first)[flat[np.cumsum(size) - 1]]
            live = np.flatnonzero(size > 1)
            while len(live):
                some = ids[live]
                ranks = self.rank(some[:, :-1], some[:, 1:])
                spot = ranks.argmin(axis=1)
                best = ranks[np.arange(len(live)), spot]
                go = best < self.none
                live, some, spot, best = live[go], some[go], spot[go], best[go]
                if not len(live):
                    break
                some[np.arange(len(live)), spot] = self.made[best]
                columns = np.arange(some.shape[1] - 1)[None]
                shifted = np.where(columns > spot[:, None], some[:, 1:], some[:, :-1])
                ids[live, :-1], ids[live, -1] = shifted, -1
                size[live] -= 1
                live = live[size[live] > 1]
            for i, row, k in zip(rows.tolist(), ids, size.tolist(), strict=True):
                out[i] = row[:k]
        return out


class Encoder:
    """Token ids of whole texts, equal to the library's with add_special_tokens=False.

    ``ids(texts)`` gives each text's as little-endian bytes of ``dtype``; ``counts(texts)`` their numbers.
    None counts as the empty text.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.tokenizer = Tokenizer.from_file(path)
        self.by_word = bool(spec["model"]["end_of_word_suffix"])
        top = max([*spec["model"]["vocab"].values(), *(t["id"] for t in spec["added_tokens"])])
        self.dtype = np.dtype("<u2" if top < 1 << 16 else "<u4")
        self.merge = Merger(spec["model"])
        #: Pre-tokens that are one token, and those merged so far.
        self.whole = {k: np.array([v], self.dtype).tobytes() for k, v in single_token_strings(path).items()}
        self.merged: dict[str, bytes] = {}
        self.memo: dict[bytes | str, bytes] = {}

    def _library(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, self.dtype).tobytes()

    def _learn(self, chunks: set) -> dict:
        """Ids of chunks that aren't memoised: whole tokens at once, other plain pre-tokens by merges, the rest by the library."""
        found, plain, new = {}, {}, {}
        for chunk in chunks:
            text = chunk.decode() if self.by_word else chunk
            if _PLAIN.match(text) and "<|" not in text:
                parts = _WORD_PRE.findall(text.lower()) if self.by_word else _BYTE_PRE.findall(text)
                if max(map(len, parts), default=0) <= LONGEST_MERGE // 2:
                    plain[chunk] = parts
                    for p in parts:
                        if p not in self.whole and p not in self.merged:
                            new[p] = None
                    continue
            found[chunk] = self._library(text)
        if len(self.merged) + len(new) > MEMO:
            for parts in plain.values():
                for p in parts:
                    if p not in self.whole:
                        new[p] = None
            self.merged = {}
        words = list(new)
        for word, ids in zip(words, self.merge([w.encode() for w in words]), strict=True):
            self.merged[word] = ids.astype(self.dtype).tobytes()
        whole, merged = self.whole.get, self.merged.get
        for chunk, parts in plain.items():
            found[chunk] = b"".join([whole(p) or merged(p) for p in parts])
        return found

    def _chunks(self, text: str | None) -> list:
        if not text:
            return []
        if self.by_word:
            return text.encode().split()
        if _ODD_SPACE.search(text):
            return _CUT.split(text)
        first, *rest = text.split(" ")
        return [first, *[" " + x for x in rest]] if first else [" " + x for x in rest]

    def _looked_up(self, texts: list[str | None]):
        """Per text its chunks, and a function from chunk to ids."""
        every = [self._chunks(t) for t in texts]
        missing = set().union(*every) - self.memo.keys()
        found = self._learn(missing)
        if len(self.memo) + len(found) > MEMO:
            self.memo, found = {}, found | self.memo
        else:
            self.memo.update((k, v) for k, v in found.items() if len(k) <= LONGEST_MEMO)
        memo = self.memo

        def get(chunk):
            return memo[chunk] if chunk in memo else found[chunk]

        whole = found.keys() <= memo.keys()
        return every, memo.__getitem__ if whole else get

    def ids(self, texts: list[str | None]) -> list[bytes]:
        every, get = self._looked_up(texts)
        return [b"".join(map(get, chunks)) for chunks in every]

    def counts(self, texts: list[str | None]) -> list[int]:
        every, get = self._looked_up(texts)
        return [sum(map(len, map(get, chunks))) // self.dtype.itemsize for chunks in every]


class RankEncoder:
    """Token ids of whole texts by a rank table that is proven to give what the merges give.

    A rank table joins any neighbours whose bytes together are a token, merges join listed pairs only.
    Inside the bytes of a token, both go through the same states as on the token alone until it is
    made, so they agree for each token that encodes alone as itself, and other tokens are never made by merges.
    The table holds just the proven ones. In the word-end vocabulary a space after each
    pre-token stands for the word end, and joins the byte before it first.
    """

    def __init__(self, path: str):
        import public_tokenizers
        import tiktoken
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.tokenizer = Tokenizer.from_file(path)
        model, merge, byte_of = spec["model"], Merger(spec["model"]), _byte_alphabet()
        end = model["end_of_word_suffix"] or ""
        self.by_word = bool(end)
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.dtype = np.dtype("<u2" if max([*model["vocab"].values(), *(t["id"] for t in spec["added_tokens"])]) < 1 << 16 else "<u4")
        order = {(m if isinstance(m, str) else " ".join(m)).replace(" ", ""): k for k, m in enumerate(model["merges"])}
        tokens = [(t, i, bool(end) and t.endswith(end)) for t, i in model["vocab"].items()]
        ranks, self.real = {}, {}
        for ended in (False, True):
            own = [(t.removesuffix(end) if ended else t, t, i) for t, i, e in tokens if e == ended]
            own = [(bytes(byte_of[c] for c in plain), t, i) for plain, t, i in own if plain and all(c in byte_of for c in plain)]
            for (raw, t, i), ids in zip(own, merge([raw for raw, _, _ in own], ended or not end), strict=True):
                if ids.tolist() == [i]:
                    raw = raw + b" " * ended
                    ranks[raw] = raw[0] if len(raw) == 1 else 256 + raw[0] if ended and len(raw) == 2 else 512 + order[t]
                    self.real[ranks[raw]] = i
        table = np.zeros(max(self.real) + 1, self.dtype)
        table[list(self.real)] = list(self.real.values())
        self.table = table
        self.encoding = tiktoken.Encoding("ranks", pat_str="[^ ]+ " if self.by_word else public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    def _library(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, self.dtype).tobytes()

    def _fast(self, text: str) -> bytes:
        if self.by_word:
            text = " ".join([*_WORD_PRE.findall(text.lower()), ""])
        return self.table[self.encoding.encode_ordinary(text)].tobytes()

    def one(self, text: str | None) -> bytes:
        """Ids of a text as little-endian bytes of ``dtype``; None counts as the empty text."""
        if not text:
            return b""
        if any(s in text for s in self.special):
            return self._library(text)
        if _PLAIN.match(text):
            return self._fast(text)
        if not self.by_word:
            return self._library(text)
        parts = _ODD_WORD.split(text)  # plain stretches and, between them, words with other characters
        return b"".join(self._library(p) if k % 2 else self._fast(p) for k, p in enumerate(parts) if p)


@lru_cache(maxsize=2)
def rank_encoder(path: str) -> RankEncoder:
    return RankEncoder(path)


@lru_cache(maxsize=4)
def encoder(path: str) -> Encoder:
    """One encoder per worker and vocabulary, so that its memo serves all tasks of the worker."""
    return Encoder(path)


def in_steps(column, step: int = 1 << 20):
    """Lists of texts of an Arrow column, each of about ``step`` characters (one text at least)."""
    some, used = [], 0
    for value in column:
        some.append(value.as_py())
        used += len(some[-1] or "")
        if used >= step:
            yield some
            some, used = [], 0
    if some:
        yield some
