"""Language of texts and of the spans of mixed texts.

A word is a run of letters. The script of its first letter narrows the candidates to the
languages learned in that script; each candidate's score is the log likelihood of the word's
letter trigrams (word ends included). Viterbi with a penalty for switching labels the words
of a text; spans are runs of equal labels, and a text's language is the one with most letters.

The model is fitted on the driver from a bounded sample (``TRAIN_ROWS``, distinct texts);
its size is bounded by the number of languages times ``BUCKETS``.

Defined cases: a text that is null or has no letter is ``und`` with score 0; with no training
text everything is ``und``; a word in a script that no language was learned in lets all compete on
the switching penalty alone; ties go to the more frequent language in training, then
alphabetically; repeated rows each get their label; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.llm.batches import bounded_sample, codepoints, slices

#: Documented bound of the training sample, in documents.
TRAIN_ROWS = 4_000
BUCKETS = 1 << 17
SWITCH = 12.0
SMOOTHING = 0.2
#: A text of more characters is read in windows of so many; bytes of text labelled at once where texts are passed on.
SLICE, PASSED = 1_000_000, 500_000
#: A language is a candidate for a script that holds this share of its words.
SCRIPT_SHARE = 0.02

#: First codepoints of ranges with one script each (0: others); fixed values from the Unicode blocks.
_RANGES = (
    (0x0, 1), (0x250, 0), (0x370, 2), (0x400, 3), (0x530, 4), (0x590, 5), (0x600, 6), (0x700, 0), (0x750, 6), (0x780, 0), (0x900, 7), (0x980, 8),
    (0xA00, 0), (0xE00, 9), (0xE80, 0), (0x10A0, 10), (0x1100, 11), (0x1200, 12), (0x1380, 0), (0x1E00, 1), (0x1F00, 2), (0x2000, 0), (0x3040, 13),
    (0x3100, 0), (0x3400, 14), (0xA000, 0), (0xAC00, 11), (0xD7B0, 0), (0xF900, 14), (0xFB00, 1), (0xFB07, 0), (0x20000, 14), (0x32000, 0),
)
_STARTS, _SCRIPTS = (np.array(x) for x in zip(*_RANGES))
SCRIPTS = 15


@cache
def _tables() -> tuple[np.ndarray, np.ndarray]:
    """For each codepoint: its one-letter lower case, 0 if it is no letter."""
    lower = np.zeros(0x110000, np.uint32)
    for c in (*range(0x3400), *range(0xA000, 0xD800), *range(0xF900, 0x20000)):
        if (ch := chr(c)).isalpha():
            lower[c] = ord(low) if len(low := ch.lower()) == 1 else c
    lower[0x3400:0xA000] = np.arange(0x3400, 0xA000)
    lower[0x20000:0x32000] = np.arange(0x20000, 0x32000)
    lower[0x4DC0:0x4E00] = 0
    return lower, lower > 0


@dataclass
class Words:
    """Words of several texts laid end to end."""

    trigram: np.ndarray  # bucket of each letter
    first: np.ndarray  # each word's first letter, as an index into trigram
    begin: np.ndarray  # each word's first codepoint in its text
    size: np.ndarray  # letters
    script: np.ndarray
    text: np.ndarray  # which text

    @classmethod
    def of(cls, texts: list[str | None]) -> Words:
        lower, _ = _tables()
        points = [codepoints(t or "") for t in texts]
        ends = np.cumsum([0] + [len(p) + 1 for p in points])
        flat = np.zeros(ends[-1] + 1, np.uint32)
        for p, at in zip(points, ends):
            flat[at + 1 : at + 1 + len(p)] = p
        low = lower[flat]
        letter = low > 0
        word = letter & ~np.concatenate([[False], letter[:-1]])
        begin = np.flatnonzero(word)
        at = np.flatnonzero(letter)
        low = np.append(low, np.uint32(0))
        mixed = low[at - 1] * np.uint32(0x9E3779B1) + low[at] * np.uint32(0x85EBCA77) + low[at + 1] * np.uint32(0xC2B2AE3D)
        mixed ^= mixed >> np.uint32(15)
        mixed *= np.uint32(0x2C1B3C6D)
        trigram = (mixed >> np.uint32(15)).astype(np.int32)
        first = np.searchsorted(at, begin)
        text = np.searchsorted(ends, begin, side="left") - 1
        script = _SCRIPTS[np.searchsorted(_STARTS, flat[begin], side="right") - 1]
        return cls(trigram, first, begin - 1 - ends[text], np.diff(np.append(first, len(at))), script, text)


@dataclass
class Model:
    languages: list[str]
    table: np.ndarray  # languages x BUCKETS, log likelihood
    scripts: np.ndarray  # SCRIPTS x languages, 0 or a large negative number
    known: np.ndarray  # scripts that some language was learned in
    prior: np.ndarray

    @classmethod
    def fit(cls, rows: Iterable[tuple[str, str]]) -> Model:
        """rows: (text, language). Equal texts of one language count once."""
        by: dict[str, set[str]] = {}
        for text, lang in rows:
            by.setdefault(lang, set()).add(text)
        names = sorted(by)
        table, scripts, size = np.zeros((len(names), BUCKETS), np.float32), np.zeros((SCRIPTS, len(names))), np.zeros(len(names))
        for i, lang in enumerate(names):
            counts = np.zeros(BUCKETS)
            texts = sorted(by[lang])
            for k in range(0, len(texts), 200):
                words = Words.of(texts[k : k + 200])
                counts += np.bincount(words.trigram, minlength=BUCKETS)
                scripts[:, i] += np.bincount(words.script, minlength=SCRIPTS)
            size[i] = len(texts)
            table[i] = np.log(counts + SMOOTHING) - np.log(counts.sum() + SMOOTHING * BUCKETS)
        share = scripts / np.maximum(1, scripts.sum(0))
        allowed = share >= SCRIPT_SHARE
        known = allowed.any(1)
        return cls(names, table, np.where(allowed, 0.0, -1e6).astype(np.float32), known, np.log((size + 1e-3) / (size.sum() + 1e-3)) * 1e-3)

    def emit(self, words: Words) -> np.ndarray:
        """words x languages."""
        out = np.stack([np.add.reduceat(row[words.trigram], words.first) for row in self.table], 1)
        out += self.scripts[words.script]
        out[~self.known[words.script]] = 0
        return out

    def label(self, words: Words) -> np.ndarray:
        """The language of each word: the best path of each text, all texts in step."""
        return self.path(self.emit(words), words.text)

    def path(self, score: np.ndarray, text: np.ndarray) -> np.ndarray:
        """The best path over scores (words x languages) within each text, whose words lie together."""
        n, k = score.shape
        counts = np.bincount(text)
        counts = counts[counts > 0]
        start = np.concatenate([[0], np.cumsum(counts)[:-1]])
        order = np.argsort(-counts, kind="stable")
        counts, start = counts[order], start[order]
        best = np.zeros((n, k), np.int8 if k < 128 else np.int32)
        delta = score[start] + self.prior
        longest = int(counts[0])
        active = np.searchsorted(-counts, -np.arange(1, longest + 1), side="right")
        own = np.arange(k)
        for t in range(1, longest):
            m = active[t]
            d = delta[:m]
            top = d.argmax(1)
            high = d.max(1)[:, None] - SWITCH
            stay = d >= high
            at = start[:m] + t
            best[at] = np.where(stay, own, top[:, None])
            delta[:m] = np.maximum(d, high) + score[at]
        path = np.zeros(n, best.dtype)
        now = delta.argmax(1)
        for t in range(longest - 1, -1, -1):
            m = active[t]
            at = start[:m] + t
            path[at] = now[:m]
            if t:
                now[:m] = best[at, now[:m]]
        return path

    def windows(self, text: str, limit: int) -> tuple[np.ndarray, np.ndarray]:
        """(scores, letters) of the words of one long text, read in windows of about ``limit`` characters that end between words.

        Of a window only a number per word and language stays; a word longer than a window is read whole."""
        scores, sizes, start = [], [], 0
        while start < len(text):
            stop = min(len(text), start + limit)
            while stop < len(text) and text[stop - 1].isalpha() and text[stop].isalpha():
                stop += 1
            words = Words.of([text[start:stop]])
            if len(words.first):
                scores.append(self.emit(words))
                sizes.append(words.size)
            start = stop
        if not scores:
            return np.zeros((0, len(self.languages)), np.float32), np.zeros(0, np.int64)
        return np.concatenate(scores), np.concatenate(sizes)


def is_held_out(doc_id: str = "doc_id"):
    return F.pmod(F.crc32(F.col(doc_id).cast("string")), F.lit(3)) == 1


def train(docs: DataFrame, rows: int = TRAIN_ROWS) -> Model:
    """Fits on about ``rows`` documents at most that have text and language."""
    known = docs.filter("text is not null and lang is not null").select("doc_id", "text", "lang")
    return Model.fit(bounded_sample(known, rows, "doc_id").select("text", "lang").toLocalIterator())


def classify(model: Model, texts: list[str | None], limit: int = SLICE) -> tuple[list[str], np.ndarray]:
    """Language of each text and the share of its letters labelled so; a text of more than ``limit`` characters by windows."""
    names, n, k = [*model.languages, "und"], len(texts), len(model.languages)
    letters = np.zeros((n, k))
    long = [i for i, t in enumerate(texts) if t and len(t) > limit]
    if k:
        for i in long:
            score, size = model.windows(texts[i], limit)
            if len(size):
                letters[i] = np.bincount(model.path(score, np.zeros(len(size), np.int64)), size, k)
        words = Words.of([None if i in long else t for i, t in enumerate(texts)] if long else texts)
        if len(words.first):
            letters += np.bincount(words.text * k + model.label(words), words.size, n * k).reshape(n, k)
    total = letters.sum(1)
    winner, share = np.full(n, k), np.zeros(n)
    if k:
        ranked = letters + np.exp(model.prior) * 1e-6
        winner = np.where(total > 0, ranked.argmax(1), k)
        share = np.where(total > 0, letters.max(1) / np.maximum(total, 1), 0.0)
    return [names[i] for i in winner], share


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, lang_pred, score (share of the letters labelled so) of every document."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, limit=SLICE):
            names, share = classify(model, part.column("text").to_pylist())
            yield pa.record_batch([part.column("doc_id"), pa.array(names, pa.string()), pa.array(share)], names=["doc_id", "lang_pred", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, lang_pred string, score double")


def spans(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, start, end (codepoints), lang of the runs of words with one label; texts without words have none."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, limit=SLICE):
            words = Words.of(part.column("text").to_pylist())
            if not len(model.languages) or not len(words.first):
                continue
            label = model.label(words)
            cut = np.flatnonzero(np.append(True, (np.diff(label) != 0) | (np.diff(words.text) != 0)))
            last = np.append(cut[1:], len(label)) - 1
            ids = part.column("doc_id").take(pa.array(words.text[cut]))
            end, lang = words.begin[last] + words.size[last], [model.languages[i] for i in label[cut]]
            columns = [ids, pa.array(words.begin[cut]), pa.array(end), pa.array(lang)]
            yield pa.record_batch(columns, names=["doc_id", "start", "end", "lang"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, start long, end long, lang string")


def identify(docs: DataFrame, *, train_rows: int = TRAIN_ROWS) -> DataFrame:
    """doc_id, held_out, lang_pred, score; the model learns from documents that are not held out."""
    held = docs.select("doc_id", "text", "lang").withColumn("held_out", F.coalesce(is_held_out(), F.lit(False)))
    model = train(held.filter(~F.col("held_out")), train_rows)
    return predict(docs, model).select("doc_id", F.coalesce(is_held_out(), F.lit(False)).alias("held_out"), "lang_pred", "score")


def keep_known(docs: DataFrame, least_share: float, *, train_rows: int = TRAIN_ROWS) -> DataFrame:
    """The rows whose text has letters, at least ``least_share`` of them in one language; other columns stay as they are.

    That language becomes ``lang`` (a string column; without one, or without any text of a known language, there is
    nothing to learn from and no row is known). Null and empty texts go; repeated rows are judged alike."""
    if "lang" not in docs.columns:
        return docs.filter("false")
    model = train(docs, train_rows)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, limit=PASSED):
            names, share = classify(model, part.column("text").to_pylist())
            at = part.schema.get_field_index("lang")
            part = part.set_column(at, part.schema.field(at), pa.array(names, part.schema.field(at).type))
            yield part.filter(pa.array((share >= least_share) & (share > 0)))

    return docs.mapInArrow(run, docs.schema)
