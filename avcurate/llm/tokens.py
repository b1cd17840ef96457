"""Byte-level BPE ids of whole texts, as the tokenizers library gives them for the same file.

Where a file's merges are numbered in the order of their ranks (checked on loading), ids come
from tiktoken's core over the same vocabulary, which is about five times as fast. Any other file,
and any text that holds the string of a special token, goes to the tokenizers library.

Edge cases: an empty text has no ids; a text of any length is encoded whole. The core's pattern
engine gives up on very long white space, so such a run is one piece by the pattern's rule (all of
it but the last character, which goes with what follows) and is encoded without the pattern.
"""

from __future__ import annotations

import json
import re

import tiktoken
from tokenizers import Tokenizer

from avcurate.llm.common import kept

#: Fixed value: the pre-tokenizer's pattern for byte-level BPE.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Characters that the pattern counts as white space.
WHITE = "\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
LONG_GAP = 4096
long_gaps = re.compile(f"[{WHITE}]{{{LONG_GAP},}}").finditer


def byte_alphabet() -> dict[str, int]:
    """The printable character that stands for each byte in byte-level vocabularies, reversed."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    other = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(other)}


class TextIds:
    """Callable: text -> ids."""

    def __init__(self, path: str):
        self.tok = Tokenizer.from_file(path)
        self.tok.no_truncation()
        self.tok.no_padding()
        self.special = [t.content for t in self.tok.get_added_tokens_decoder().values()]
        self.fast, self.piece = self._core(path)

    @staticmethod
    def _core(path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, pre, back = spec["model"], spec.get("pre_tokenizer") or {}, byte_alphabet()
        merges = [m.split(" ") if isinstance(m, str) else m for m in model.get("merges", [])]
        vocab = model["vocab"]
        usual = (
            model.get("type") == "BPE" and pre.get("type") == "ByteLevel" and pre.get("use_regex") and not pre.get("add_prefix_space")
            and spec.get("normalizer") is None and not model.get("end_of_word_suffix") and not model.get("ignore_merges")
            and all(vocab.get(a + b) == 256 + i for i, (a, b) in enumerate(merges))
        )
        if not usual:
            return None, None
        ranks = {bytes(back[c] for c in token): i for token, i in vocab.items() if all(c in back for c in token)}
        return [tiktoken.Encoding("of_file", pat_str=p, mergeable_ranks=ranks, special_tokens={}).encode_ordinary for p in (PATTERN, "(?s:.+)")]

    def __call__(self, text: str) -> list[int]:
        if self.fast is None or any(s in text for s in self.special):
            return self.tok.encode(text, add_special_tokens=False).ids
        if len(text) < LONG_GAP:
            return self.fast(text)
        ids, at = [], 0
        for gap in long_gaps(text):
            end = gap.end() - (gap.end() < len(text))
            ids += self.fast(text[at : gap.start()]) + self.piece(text[gap.start() : end])
            at = end
        return ids + self.fast(text[at:])


def ids_of(path: str) -> TextIds:
    """One for a worker process, across its tasks."""
    return kept(("ids", path), lambda: TextIds(path))
