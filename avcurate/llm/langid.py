"""Language identification of whole texts, with spans of mixed language.

A word is a run of letters of one script, of at most 64; a longer run is several words. Its script (by ranges of code points) narrows the languages to those that use the script in
the training rows. Each word gets a score for each candidate: its log-probability in the language
where training saw it, else that of its character trigrams. Viterbi over the words, with a penalty
for each switch, labels spans; a document has the language of most of its letters, and its score
is that language's share of them.

Training reads rows with text and lang whose crc32(doc_id as text) mod 5 is not 0, at most
``fit_rows`` of them on average, chosen by a hash of the id; the model keeps all words and trigrams
that these rows hold ``least`` times or more, at most 1 / ``least`` of the sample's words and letters,
and it goes to the tasks with the code. Unseen words are scored by their trigrams.

Edge cases: a null text, and one without letters, is ``und`` with score 0; letters of scripts that
no training row has give the most frequent language with score 0; without training rows every
text is ``und``; ties go to the first language by name; a text of any length is read whole;
repeated rows give repeated results; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import re
import uuid
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache
from itertools import groupby

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from avcurate.llm.common import kept, map_values, renamed, spread

#: First code points of ranges of scripts.
SCRIPT_RANGES = (
    (0x0041, "latin"), (0x0370, "greek"), (0x0400, "cyrillic"), (0x0530, "armenian"), (0x0590, "hebrew"), (0x0600, "arabic"),
    (0x0700, "other"), (0x0900, "devanagari"), (0x0980, "bengali"), (0x0A00, "other"), (0x0B80, "tamil"), (0x0C00, "other"),
    (0x0E00, "thai"), (0x0E80, "other"), (0x10A0, "georgian"), (0x1100, "hangul"), (0x1200, "other"), (0x1E00, "latin"),
    (0x1F00, "greek"), (0x2000, "other"), (0x3040, "kana"), (0x3100, "other"), (0x3130, "hangul"), (0x3190, "other"),
    (0x3400, "han"), (0xA000, "other"), (0xAC00, "hangul"), (0xD7B0, "other"), (0xF900, "han"), (0xFB00, "latin"), (0xFB13, "other"), (0x20000, "han"), (0x30000, "other"),
)
STARTS, SCRIPTS = [a for a, _ in SCRIPT_RANGES], [s for _, s in SCRIPT_RANGES]
LONGEST = 64  # letters of a word; a longer run of letters is cut into words that cover it
letter_runs, cut_runs = re.compile(r"[^\W\d_]+").findall, re.compile(rf"[^\W\d_]{{1,{LONGEST}}}").findall
UNDETERMINED = "und"


@lru_cache(1 << 16)
def script_of_letter(letter: str) -> str:
    return SCRIPTS[max(0, bisect_right(STARTS, ord(letter)) - 1)]


def find_words(text: str) -> list[str]:
    """Runs of letters of one script, long ones in pieces."""
    if text.isascii() or len({script_of_letter(c) for c in set(text) if c.isalpha()}) < 2:
        return cut_runs(text)
    out = []
    for run in letter_runs(text):
        for part in [run] if run.isascii() else map("".join, (g for _, g in groupby(run, script_of_letter))):
            out += [part] if len(part) <= LONGEST else [part[i : i + LONGEST] for i in range(0, len(part), LONGEST)]
    return out


def script_of(word: str) -> str:
    letter = next((c for c in word if c.isalpha()), None)
    return script_of_letter(letter) if letter else "none"


def grams_of(word: str) -> list[str]:
    w = f"^{word}$"
    return [w[i : i + 3] for i in range(len(w) - 2)]


class Model:
    """Scores of words for the languages, ``langs`` in the order of their names."""

    def __init__(self, counts: list[tuple[str, str, str, int]], clip: float = 6.0, script_share: float = 0.01):
        """counts: (kind, language, item, count) with kinds word, gram, script, total."""
        self.langs = sorted({lang for _, lang, _, _ in counts})
        self.token = uuid.uuid4().hex
        self.clip, k = clip, len(self.langs)
        at = {lang: i for i, lang in enumerate(self.langs)}
        tables: dict[str, dict[str, np.ndarray]] = {kind: {} for kind in ("word", "gram", "script", "total")}
        for kind, lang, item, n in counts:
            tables[kind].setdefault(item, np.zeros(k))[at[lang]] += n
        zero = np.zeros(k)
        self.words_total, self.grams_total = (tables["total"].get(x, zero) for x in ("word", "gram"))
        self.words, self.word_rows = self._smooth(tables["word"], self.words_total)
        self.grams, self.gram_rows = self._smooth(tables["gram"], self.grams_total)
        all_scripts = sum(tables["script"].values(), zero)
        self.scripts = {s: c >= script_share * np.maximum(all_scripts, 1) for s, c in tables["script"].items()}
        self.prior = int(np.argmax(all_scripts)) if k else 0

    def _smooth(self, table: dict[str, np.ndarray], total: np.ndarray, a: float = 0.5) -> tuple[dict[str, int], np.ndarray]:
        """Row of each item, and rows of log-probabilities; the last row is of items that training hasn't seen."""
        c = np.array([*table.values(), np.zeros(len(self.langs))]).reshape(len(table) + 1, len(self.langs))
        return {x: i for i, x in enumerate(table)}, np.log((c + a) / (total + a * len(c)))

    def scores(self, words: list[str]) -> np.ndarray:
        """A row for each word: relative to its best language, not below -clip; zeros where the script says nothing; -2 clip for languages of other scripts."""
        out = np.zeros((len(words), len(self.langs)))
        known = np.fromiter((self.words.get(w, -1) for w in words), np.int64, len(words))
        out[known >= 0] = self.word_rows[known[known >= 0]]
        new = np.flatnonzero(known < 0)
        if len(new):
            grams = [[self.grams.get(g, -1) for g in grams_of(words[i])] for i in new]
            first = np.cumsum([0, *map(len, grams[:-1])])
            out[new] = np.add.reduceat(self.gram_rows[np.concatenate(grams)], first, axis=0)
        nothing = np.zeros(len(self.langs), bool)
        may = np.array([self.scripts.get(script_of(w), nothing) for w in words])
        out = np.maximum(out - np.where(may, out, -1e9).max(axis=1, keepdims=True), -self.clip)
        out = np.where(may, out, -2 * self.clip)
        out[~may.any(axis=1)] = 0
        return out


class Scorer:
    """Rows of scores and letters by word, for the words of a task; a bounded number is kept."""

    def __init__(self, model: Model, cache_words: int = 300_000):
        self.model, self.most = model, cache_words
        self.clear()

    def clear(self) -> None:
        self.rows: dict[str, int] = {}
        self.scores = np.zeros((1024, len(self.model.langs)), np.float32)
        self.letters = np.zeros(1024, np.int32)

    def ids(self, words: list[str]) -> np.ndarray:
        rows = self.rows
        new = [w for w in set(words) if w not in rows]
        if new:
            end = len(rows) + len(new)
            while end > len(self.scores):
                self.scores = np.concatenate([self.scores, np.zeros_like(self.scores)])
                self.letters = np.concatenate([self.letters, np.zeros_like(self.letters)])
            self.scores[len(rows) : end] = self.model.scores(new)
            self.letters[len(rows) : end] = [sum(map(str.isalpha, w)) for w in new]
            rows.update(zip(new, range(len(rows), end)))
        return np.fromiter(map(rows.__getitem__, words), np.int32, len(words))


def scorer_of(sent) -> Scorer:
    """One for a worker process, across its tasks."""
    return kept(("langid", sent.value.token), lambda: Scorer(sent.value))


def stays(s: np.ndarray, penalty: float) -> int | None:
    """The label that the best path has from end to end, where that is certain without the path.

    Leaving label L for words a..b gains at most the sum of the others' best lead over L there. If
    no stretch of words has a lead above the penalty of one switch, no path beats staying.
    """
    if s.shape[1] < 2:
        return 0
    at = int(s.sum(axis=0, dtype=np.float64).argmax())
    lead = np.delete(s, at, axis=1).max(axis=1).astype(np.float64) - s[:, at]
    summed = np.cumsum(lead)
    lowest = np.minimum.accumulate(np.r_[0.0, summed[:-1]])
    return at if (summed - lowest).max() <= penalty else None


def viterbi(ids: list[np.ndarray], scores: np.ndarray, penalty: float) -> list[np.ndarray]:
    """The best label of every word of every document, for all documents in step."""
    k = scores.shape[1]
    order = np.argsort([-len(x) for x in ids], kind="stable")
    lens = np.array([len(ids[i]) for i in order])
    flat = np.concatenate([ids[i] for i in order]) if len(ids) else np.empty(0, np.int32)
    starts = np.cumsum(lens) - lens
    back = np.empty((len(flat), k), np.uint8)
    here = np.arange(k, dtype=np.uint8)
    best = np.zeros((len(ids), k))
    longest = int(lens[0]) if len(lens) else 0
    active = np.searchsorted(-lens, -np.arange(longest), side="left")
    for t in range(longest):
        n = active[t]
        v, at = best[:n], starts[:n] + t
        top = v.argmax(axis=1)
        switch = v[np.arange(n), top] - penalty
        stay = v >= switch[:, None]
        back[at] = np.where(stay, here, top[:, None].astype(np.uint8))
        best[:n] = np.where(stay, v, switch[:, None]) + scores[flat[at]]
    label = np.empty(len(flat), np.uint8)
    now = best.argmax(axis=1).astype(np.uint8)
    for t in range(longest - 1, -1, -1):
        n = active[t]
        at = starts[:n] + t
        label[at] = now[:n]
        now[:n] = back[at, now[:n]]
    out: list[np.ndarray] = [np.empty(0, np.uint8)] * len(ids)
    for j, i in enumerate(order):
        out[i] = label[starts[j] : starts[j] + lens[j]]
    return out


# --- training -------------------------------------------------------------------------------------


def training_rows(docs: DataFrame, fit_rows: int, seed: int = 1) -> DataFrame:
    """lang, text: rows that may be learned from, a bounded number of them on average."""
    rows = docs.where("text is not null and lang is not null and doc_id is not null").where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 != 0)
    n = rows.count()
    if n > fit_rows:
        rows = rows.where(F.pmod(F.xxhash64(F.lit(seed), "doc_id"), F.lit(1 << 20)) < int(fit_rows / n * (1 << 20)))
    return rows.select("lang", "text")


def fit(docs: DataFrame, fit_rows: int = 8000, least: int = 3) -> Model:
    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            found: Counter = Counter()
            for lang, text in zip(b.lang, b.text):
                words = Counter(find_words(text.lower()))
                grams, scripts = Counter(), Counter()
                for w, n in words.items():
                    scripts[script_of(w)] += n
                    for g in grams_of(w):
                        grams[g] += n
                for kind, c in (("word", words), ("gram", grams), ("script", scripts)):
                    for item, n in c.items():
                        found[kind, lang, item] += n
                    found["total", lang, kind] += c.total()
            yield pd.DataFrame([(*k, n) for k, n in found.items()], columns=["kind", "lang", "item", "n"])

    summed = (
        spread(training_rows(docs, fit_rows)).mapInPandas(count, "kind string, lang string, item string, n long")
        .groupBy("kind", "item", "lang").agg(F.sum("n").alias("n"))
        .groupBy("kind", "item").agg(F.sum("n").alias("all"), F.map_from_entries(F.collect_list(F.struct("lang", "n"))).alias("by"))
        .where(F.col("kind").isin("script", "total") | (F.col("all") >= least))
    )
    return Model([(r.kind, lang, r.item, n) for r in summed.collect() for lang, n in r.by.items()])


# --- prediction -------------------------------------------------------------------------------------


def label(texts: list[str | None], scorer: Scorer, penalty: float) -> list[tuple[str, float, list[tuple[str, int, int]]]]:
    """(language, score, spans of words (language, first, count)) of each text."""
    model = scorer.model
    ids = [scorer.ids(find_words(t.lower())) if t and model.langs else np.empty(0, np.int32) for t in texts]
    scores, letters = scorer.scores, scorer.letters
    paths: list[np.ndarray] = []
    open_ = []
    for i, x in enumerate(ids):
        at = stays(scores[x], penalty) if len(x) else None
        paths.append(np.full(len(x), at or 0, np.uint8))
        if len(x) and at is None:
            open_.append(i)
    for i, path in zip(open_, viterbi([ids[i] for i in open_], scores, penalty)):
        paths[i] = path
    out = []
    for x, path in zip(ids, paths):
        weight = letters[x].astype(np.float64)
        if not weight.sum():
            out.append((UNDETERMINED, 0.0, []))
            continue
        said = np.where(scores[x].any(axis=1), weight, 0)
        share = np.bincount(path, said, len(model.langs)) / weight.sum()
        best = int(share.argmax()) if share.any() else model.prior
        cut = np.flatnonzero(np.diff(path)) + 1
        lo, hi = np.r_[0, cut], np.r_[cut, len(path)]
        out.append((model.langs[best], float(share[best]), [(model.langs[path[a]], int(a), int(b - a)) for a, b in zip(lo, hi)]))
    return out


def identify(docs: DataFrame, model: Model, penalty: float = 8.0, spans: bool = False, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """*keep, lang_pred, score, mixed (another language holds a span) of every row; spans adds the spans."""
    rows = docs.select(*keep, F.col("text").alias("_text"))
    sent = docs.sparkSession.sparkContext.broadcast(model)
    added = "lang_pred string, score double, mixed boolean" + ", spans array<struct<lang:string,first:int,words:int>>" * spans

    def make():
        scorer = scorer_of(sent)

        def some(texts: list[str | None]) -> list[list]:
            if len(scorer.rows) > scorer.most:
                scorer.clear()
            found = label(texts, scorer, penalty)
            out = [[x[0] for x in found], [x[1] for x in found], [len(x[2]) > 1 for x in found]]
            return out + [[[{"lang": a, "first": i, "words": n} for a, i, n in x[2]] for x in found]] * spans

        return some

    return map_values(spread(rows), "_text", make, added)


def identify_documents(docs: DataFrame, **options) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every document."""
    found = identify(docs.select("doc_id", "text"), fit(docs), **options)
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0
    return found.select("doc_id", F.coalesce(held, F.lit(False)).alias("held_out"), "lang_pred", "score", "mixed")


def keep_identified(docs: DataFrame, least: float = 0.2) -> DataFrame:
    """The documents whose text has a language that holds at least the share ``least`` of its letters."""
    rows = renamed(docs)
    found = identify(rows, fit(docs), keep=tuple(rows.columns))
    return found.where((F.col("lang_pred") != UNDETERMINED) & (F.col("score") >= least)).select(rows.columns).toDF(*docs.columns)
