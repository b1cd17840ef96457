"""BPE with word ends, by forced-boundary splitting.

A pair of neighbouring bytes that occurs inside no token of the vocabulary can never end up in one
token, so a word may be cut between them. The fragments are encoded independently, each by merges
of least rank, and their ids are concatenated; only a word's last fragment carries the word end.
Fragments and words repeat, so a task keeps the results of a bounded number of both.

Decoding looks up the token of every id and joins the tokens by one space, as the tokenizers
library does for a file without a decoder, special tokens included.

Edge cases: a null or empty text has no ids; white space alone has none; strings of special tokens
become their ids, as the library does; words of any length are cut and encoded whole; an empty
table gives no rows; repeated rows give repeated results; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import re
import unicodedata
from collections.abc import Iterator

import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from avcurate.llm.common import kept, map_values, spread
from avcurate.llm.tokens import byte_alphabet

END = "</w>"
#: What the file's normaliser and splitter match.
WORDS = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
SPACES = "\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
#: The same words for texts of Latin-1 characters only, for the faster engine of the standard library.
LATIN_LETTERS = "A-Za-zªµºÀ-ÖØ-öø-ÿ"
LATIN_DIGITS = "0-9²³¹¼-¾"
LATIN_WORDS = rf"'s|'t|'re|'ve|'m|'ll|'d|[{LATIN_LETTERS}]+|[{LATIN_DIGITS}]|[^\t-\r \x85\xa0{LATIN_LETTERS}{LATIN_DIGITS}]+"
CACHE_WORDS, CACHE_FRAGMENTS = 300_000, 300_000


def merge(symbols: list[str], ranks: dict[tuple[str, str], int]) -> list[str]:
    """Merges of least rank first, the leftmost of equals first; a heap keeps long fragments cheap."""
    if len(symbols) < 2:
        return symbols
    left, right = list(range(-1, len(symbols) - 1)), list(range(1, len(symbols) + 1))
    live = list(symbols)
    heap = [(r, i, a + b) for i, (a, b) in enumerate(zip(symbols, symbols[1:])) if (r := ranks.get((a, b))) is not None]
    heapq.heapify(heap)
    n = len(symbols)
    while heap:
        _, i, joined = heapq.heappop(heap)
        j = right[i]
        if live[i] is None or j >= n or live[i] + live[j] != joined:
            continue
        live[i], live[j], right[i] = joined, None, right[j]
        if right[j] < n:
            left[right[j]] = i
            if (r := ranks.get((joined, live[right[j]]))) is not None:
                heapq.heappush(heap, (r, i, joined + live[right[j]]))
        if (k := left[i]) >= 0 and (r := ranks.get((live[k], joined))) is not None:
            heapq.heappush(heap, (r, k, live[k] + joined))
    return [s for s in live if s is not None]


class Bpe:
    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.vocab: dict[str, int] = model["vocab"]
        pairs = (tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"])
        self.ranks = {p: i for i, p in enumerate(pairs)}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.tokens = {i: t for t, i in (self.vocab | self.special).items()}
        self.chars = [c for c, _ in sorted(byte_alphabet().items(), key=lambda x: x[1])]
        self.inside = {(a, b) for t in self.vocab for bare in [t.removesuffix(END)] for a, b in zip(bare, bare[1:])}
        self.split = regex.compile("|".join(map(regex.escape, self.special))) if self.special else None
        self.fragments: dict[tuple[str, bool], list[int]] = {}
        self.words = _Words(self)
        self.tokens_of = _Tokens(self)
        self.find = regex.compile(WORDS.replace("\\s", SPACES)).findall
        self.find_latin = re.compile(LATIN_WORDS).findall

    def cuts(self, word: str) -> list[str]:
        """The fragments of a word in byte characters."""
        inside, out, start = self.inside, [], 0
        for i in range(1, len(word)):
            if (word[i - 1], word[i]) not in inside:
                out.append(word[start:i])
                start = i
        return [*out, word[start:]]

    def fragment_ids(self, fragment: str, last: bool) -> list[int]:
        got = self.fragments.get((fragment, last))
        if got is None:
            symbols = list(fragment)
            if last:
                symbols[-1] += END
            got = [self.vocab[s] for s in merge(symbols, self.ranks)]
            if len(self.fragments) < CACHE_FRAGMENTS and len(fragment) < 64:
                self.fragments[fragment, last] = got
        return got

    def word_ids(self, word: str) -> list[int]:
        parts = self.cuts("".join([self.chars[b] for b in word.encode("utf-8")]))
        ids = []
        for i, part in enumerate(parts, 1):
            ids += self.fragment_ids(part, i == len(parts))
        return ids

    def normal_words(self, text: str) -> list[str]:
        if not unicodedata.is_normalized("NFC", text):
            text = unicodedata.normalize("NFC", text)
        text = (text.replace("Σ", "σ") if "Σ" in text else text).lower()
        try:
            text.encode("latin-1")
        except UnicodeEncodeError:
            return self.find(text)
        return self.find_latin(text)

    def runs(self, text: str) -> Iterator[tuple[list[str], int | None]]:
        """The words between special tokens, and the special token that follows them."""
        if self.split is None or not any(s in text for s in self.special):
            yield self.normal_words(text), None
            return
        at = 0
        for m in self.split.finditer(text):
            yield self.normal_words(text[at : m.start()]), self.special[m[0]]
            at = m.end()
        yield self.normal_words(text[at:]), None

    def encode(self, text: str) -> list[int]:
        return [int(i) for i in self.encode_decimal(text).split()]

    def encode_decimal(self, text: str) -> str:
        """The ids in decimal, joined by one space."""
        out = []
        for words, special in self.runs(text):
            out += map(self.words.__getitem__, words)
            if special is not None:
                out.append(str(special))
        return " ".join(out)

    def decode_decimal(self, ids: str) -> str:
        return " ".join(map(self.tokens_of.__getitem__, ids.split(" "))) if ids else ""

    def decode(self, ids: list[int]) -> str:
        return " ".join([self.tokens[i] for i in ids])


class _Words(dict):
    def __init__(self, bpe: Bpe):
        super().__init__()
        self.bpe = bpe

    def __missing__(self, word: str) -> str:
        got = " ".join(map(str, self.bpe.word_ids(word)))
        if len(self) < CACHE_WORDS and len(word) < 64:
            self[word] = got
        return got


class _Tokens(dict):
    """Decimal id -> token."""

    def __init__(self, bpe: Bpe):
        super().__init__()
        self.bpe = bpe

    def __missing__(self, decimal: str) -> str:
        self[decimal] = got = self.bpe.tokens[int(decimal)]
        return got


def bpe_of(path: str) -> Bpe:
    """One for a worker process, across its tasks."""
    return kept(("bpe", path), lambda: Bpe(path))


def encode_documents(docs: DataFrame, tokenizer: str, with_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256; with_ids adds ids (array) and the decoded text."""
    added = "n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>, decoded string" * with_ids

    def make():
        bpe, sha = bpe_of(tokenizer), hashlib.sha256

        def one(text: str) -> tuple:
            ids = bpe.encode_decimal(text)
            decoded = bpe.decode_decimal(ids)
            row = (ids.count(" ") + 1 if ids else 0, sha(ids.encode()).hexdigest(), sha(decoded.encode("utf-8")).hexdigest())
            return row + (([int(i) for i in ids.split()], decoded) if with_ids else ())

        return lambda texts: list(zip(*[one(t or "") for t in texts]))

    return map_values(spread(docs.select(F.col("doc_id").cast("long"), "text")), "text", make, added)
