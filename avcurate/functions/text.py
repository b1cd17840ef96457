"""Transcript measures as column expressions; lengths and distances count code points.

A transcript is a string. A long one is a sequence of utterances, divided by ``BREAK``: the n-th
utterance of a hypothesis answers the n-th of its reference, and distances are sums over them, so a
transcript of any length is measured whole in time linear in its length.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

BREAK = "\x1e"


def _c(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def utterances(text: Column | str, chars: int = 160) -> Column:
    """The whole text as a transcript of utterances of at most so many characters."""
    parts = F.regexp_extract_all(F.translate(_c(text), BREAK, " "), F.lit(f"(?s).{{1,{chars}}}"), F.lit(0))
    return F.array_join(parts, BREAK)


def by_utterance(text: Column | str, f: Callable[[Column], Column]) -> Column:
    """``f`` of each utterance."""
    return F.array_join(F.transform(F.split(_c(text), BREAK), f), BREAK)


def plain(text: Column | str) -> Column:
    """The text without its breaks."""
    return F.replace(_c(text), F.lit(BREAK), F.lit(""))


def sum_over(hyp: Column | str, ref: Column | str, f: Callable[[Column, Column], Column]) -> Column:
    """Sum of ``f`` (a count) over utterances that answer each other; one without an answer meets the empty one."""
    none = F.lit("")
    each = F.zip_with(F.split(_c(hyp), BREAK), F.split(_c(ref), BREAK), lambda h, r: f(F.coalesce(h, none), F.coalesce(r, none)))
    return F.aggregate(each, F.lit(0).cast("bigint"), lambda total, n: total + n)


def edits(h: Column, r: Column) -> Column:
    """Edit distance of two utterances; where they are about equally long a narrow band is tried first."""
    full = F.levenshtein(h, r)
    near = F.abs(F.length(h) - F.length(r)) <= 4
    return F.when(h == r, 0).when(near, F.coalesce(F.nullif(F.levenshtein(h, r, 8), F.lit(-1)), full)).otherwise(full)


def distance(hyp: Column | str, ref: Column | str) -> Column:
    return sum_over(hyp, ref, edits)


def longer_length(hyp: Column | str, ref: Column | str) -> Column:
    return sum_over(hyp, ref, lambda h, r: F.greatest(F.length(h), F.length(r)))


def length_gap(hyp: Column | str, ref: Column | str) -> Column:
    """What the distance is at least."""
    return sum_over(hyp, ref, lambda h, r: F.abs(F.length(h) - F.length(r)))


def asr_confidence(hyp: Column | str, ref: Column | str) -> Column:
    """1 - distance / longer length; 1 where both are empty, null where either is null."""
    longer = longer_length(hyp, ref)
    return F.when(longer == 0, 1.0).otherwise(1.0 - F.try_divide(distance(hyp, ref), longer))


def asr_confidence_bounded(hyp: Column | str, ref: Column | str, k: Column) -> Column:
    """The same where the distance is at most k, else null: work stops once utterances have used up k, and each stays in a band of what is left."""
    h, r, none = _c(hyp), _c(ref), F.lit("")
    longer = longer_length(h, r)
    pairs = F.zip_with(F.split(h, BREAK), F.split(r, BREAK), lambda x, y: F.struct(F.coalesce(x, none).alias("h"), F.coalesce(y, none).alias("r")))
    bound = k.cast("int")

    def add(used: Column, pair: Column) -> Column:
        d = F.call_function("levenshtein", pair["h"], pair["r"], bound - used)
        return F.when(used < 0, used).otherwise(F.element_at(F.transform(F.array(d), lambda x: F.when(x < 0, -1).otherwise(used + x)), 1))

    d = F.aggregate(pairs, F.lit(0), add)
    return F.when((longer == 0) & (k >= 0), 1.0).when((k >= 0) & (d >= 0), 1.0 - F.try_divide(d, longer))


def cer(hyp: Column | str, ref: Column | str) -> Column:
    """Distance / reference length; 0 where both are empty, null where the reference alone is."""
    n = F.length(plain(ref))
    return F.when((F.length(plain(hyp)) == 0) & (n == 0), 0.0).when(n > 0, distance(hyp, ref) / n)


def comprehensive_score(cer_: Column | str, sim: Column | str, alpha: float | Column = 0.5, clip: bool = False) -> Column:
    """(1 - alpha)(1 - CER) + alpha * similarity; not clipped unless asked for."""
    a = alpha if isinstance(alpha, Column) else F.lit(alpha)
    s = (1 - a) * (1 - _c(cer_)) + a * _c(sim)
    return F.greatest(F.lit(0.0), F.least(F.lit(1.0), s)) if clip else s


LETTERS = "abcdefghijklmnopqrstuvwxyz"


def letter_vector(text: Column | str) -> Column:
    """Counts of the 26 letters of the lower-cased text, which is bound once for all of them."""
    counts = lambda t: F.array(*[(F.length(t) - F.length(F.replace(t, F.lit(c), F.lit("")))).cast("double") for c in LETTERS])
    return F.element_at(F.transform(F.array(F.lower(_c(text))), counts), 1)


def route_mode(prompt: Column | str) -> tuple[Column, Column]:
    """(mode, payload) of a prompt with a leading command; an unknown command gives the mode ``error``."""
    p = _c(prompt)
    mode = F.regexp_extract(p, r"^/(translate|chat)\b", 1)
    return F.when(mode == "", "error").otherwise(mode), F.trim(F.regexp_replace(p, r"^/(translate|chat)\b", ""))


def strip_html(html: Column | str) -> Column:
    """Visible text of a page: no scripts, styles, comments or tags; common entities resolved; spaces squeezed."""
    x = F.regexp_replace(_c(html), r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    x = F.regexp_replace(F.regexp_replace(x, r"(?s)<!--.*?-->", " "), r"(?s)<[^>]*>", " ")
    for entity, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        x = F.replace(x, F.lit(entity), F.lit(char))
    return F.trim(F.regexp_replace(x, r"[ \t\r\n]+", " "))
