"""Line-first cleaning, then a verdict on the document.

Every line is judged alone: by its punctuation, as navigation, as boilerplate. Failing lines are removed; a document is
rejected when its base figures fail or when the removed lines hold too much of its text. Words are runs without
ASCII white space; lines are what lies between line feeds.

A null text has no lines and no words, like an empty one, and is rejected for having too few words. A row's verdict
depends on its text alone, so repeated rows get the same verdict; null ids are carried through.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from pathlore.llm.common import map_batches

#: Base limits: least words; most percent of words in repeated windows; words of a window.
LEAST_WORDS, MOST_REPEATED, WINDOW = 10, 20, 5
#: Line limits: share of marks among characters, share of separators among words, words of a line that capitals are judged in, share of capitals.
MOST_MARKS, MOST_SEPARATORS, BARE_WORDS, MOST_CAPITALS = 0.10, 0.30, 8, 0.8
#: Share of the words that the removed lines may hold.
MOST_REMOVED = 0.5
#: Phrases of boilerplate lines, in lower case.
BOILERPLATE = (
    "all rights reserved",
    "accept cookies",
    "click here",
    "cookie policy",
    "enable javascript",
    "javascript is disabled",
    "log in to",
    "lorem ipsum",
    "powered by",
    "privacy policy",
    "sign up for",
    "skip to content",
    "subscribe to our",
    "terms of service",
    "terms of use",
    "use cookies",
)
#: Marks that count as symbols; separators of navigation lines.
SYMBOLS, SEPARATORS = "#*$%&|<>", ("|", "»", "›", "•", "·", "/", "::", "-->", "→")
SPACES = " \t\n\x0b\x0c\r"
MARKS = re.compile("[" + re.escape(SYMBOLS) + "]")
PHRASES = re.compile("|".join(map(re.escape, BOILERPLATE)))
REASONS = ("punctuation", "navigation", "boilerplate")


def judge_line(line: str, words: list[str]) -> str | None:
    """The rule that a line fails, or None. A line without words is kept: it parts paragraphs."""
    if not words:
        return None
    if PHRASES.search(line.lower()):
        return "boilerplate"
    if sum(w in SEPARATORS for w in words) > MOST_SEPARATORS * len(words):
        return "navigation"
    marks = len(MARKS.findall(line))
    if marks > MOST_MARKS * len(line):
        return "punctuation"
    if len(words) > BARE_WORDS:
        letters = [c for c in line if c.isalpha()]
        if len(letters) > 20 and line.count("!") > len(words) * MOST_SEPARATORS and sum(map(str.isupper, letters)) > MOST_CAPITALS * len(letters):
            return "punctuation"
    return None


def repeated_words(words: list, window: int = WINDOW) -> int:
    """Words inside windows of ``window`` words that occur twice or more in the text."""
    n = len(words) - window + 1
    if n < 2:
        return 0
    number = {w: i for i, w in enumerate(dict.fromkeys(words))}
    ids = np.fromiter(map(number.__getitem__, words), "int64", len(words))
    key, kinds = ids[:n].copy(), len(number)
    for k in range(1, window):
        if int(key.max()) + 1 > (1 << 62) // kinds:
            key = np.unique(key, return_inverse=True)[1]
        key = key * kinds + ids[k : n + k]
    order = np.argsort(key, kind="stable")
    same = key[order][1:] == key[order][:-1]
    if not same.any():
        return 0
    twice = np.zeros(n, bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    edge = np.zeros(len(words) + 1, "int64")
    edge[:n] += twice
    edge[window : n + window] -= twice
    return int((np.cumsum(edge)[:-1] > 0).sum())


def measure(text: str | None) -> dict:
    """Base figures, the verdict, and what the line rules removed."""
    text = text or ""
    raw = text.encode("utf-8", "replace")
    words = raw.split()
    seen: set[str] = set()
    dup, removed_words, kept_lines = 0, 0, []
    failed = dict.fromkeys(REASONS, 0)
    for line in text.split("\n"):
        own = [w.decode() for w in line.encode("utf-8", "replace").split()]
        if own:
            dup += line in seen
            seen.add(line)
        why = judge_line(line, own)
        if why:
            failed[why] += 1
            removed_words += len(own)
        else:
            kept_lines.append(line)
    n, repeated = len(words), repeated_words(words)
    base_failed = n < LEAST_WORDS or 100 * repeated > MOST_REPEATED * n
    too_much = removed_words > MOST_REMOVED * n
    return {
        "n_words": n,
        "word_chars": len(text) - sum(map(text.count, SPACES)),
        "n_symbols": len(MARKS.findall(text)),
        "n_dup_lines": dup,
        "n_repeat_words": repeated,
        "base_failed": base_failed,
        "kept": not base_failed and not too_much,
        "removed_words": removed_words,
        **{f"{r}_lines": failed[r] for r in REASONS},
        "cleaned": "\n".join(kept_lines),
    }


FIELDS = {"n_words": "long", "word_chars": "long", "n_symbols": "long", "n_dup_lines": "long", "n_repeat_words": "long", "base_failed": "boolean", "kept": "boolean", "removed_words": "long", **{f"{r}_lines": "long" for r in REASONS}}


def assess(docs: DataFrame, with_text: bool = False) -> DataFrame:
    """doc_id and the figures of ``measure``; with the cleaned text if asked for."""
    fields = FIELDS | ({"cleaned": "string"} if with_text else {})
    kinds = {"long": pa.int64(), "boolean": pa.bool_(), "string": pa.string()}

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        found = [measure(t.as_py()) for t in batch.column("text")]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array([f[k] for f in found], kinds[t]) for k, t in fields.items())], ["doc_id", *fields])

    return map_batches(docs.select("doc_id", "text"), work, "doc_id long, " + ", ".join(f"{k} {t}" for k, t in fields.items()))
