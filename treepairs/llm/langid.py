"""Language identification: words first, then ever shorter character n-grams.

The model holds, for each language, log frequencies of its most frequent words and of character n-grams of each order.
A known word is scored by its word frequencies; an unseen one by the longest order of n-grams of which the model knows
any, down to single characters. A document's score is the softmax over languages of its summed word scores, tempered by
the square root of its number of words.

The classifier is fitted on a bounded sample: the ``max_docs`` training documents with the smallest digests of their ids.
The counts over the sample are made in Spark and cut to at most the ``max_words`` and ``max_grams`` most frequent entries per
language (and order), so the broadcast model has a fixed bound for each language.

Defined cases: null text, or one without a letter, is ``und`` with score 0; rows with a null language are not learnt
from, nor are rows with a null id, which are predicted and not held out; with nothing to learn from every text is ``und``;
ties go to the language that sorts first; rows that repeat an id or a text are predicted alike, each by its text; very long
texts are scored whole; other columns are ignored by :func:`identify` and kept by :func:`keep_identified`.
"""

from __future__ import annotations

import re
import sys
import unicodedata
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import checkpointed, tidy

MAX_DOCS, MAX_WORDS, MAX_GRAMS, ORDERS = 20_000, 20_000, 5_000, (4, 3, 2, 1)
#: Words whose scores a worker keeps.
KEPT_WORDS = 300_000


def _numerals() -> str:
    """Word characters that are no letters and no decimal digits (fractions, superscripts, number letters), as ranges."""
    codes = [c for c in range(sys.maxunicode + 1) if chr(c).isalnum() and unicodedata.category(chr(c))[0] != "L"]
    runs: list[list[int]] = []
    for c in codes:
        if runs and runs[-1][1] == c - 1:
            runs[-1][1] = c
        else:
            runs.append([c, c])
    return "".join(f"{chr(a)}-{chr(b)}" for a, b in runs)


#: A run of letters, of Unicode categories L only.
_WORD = re.compile(rf"[^\W\d_{_numerals()}]+")


def grams(word: str, order: int) -> list[str]:
    padded = f"^{word}$" if order > 1 else word
    return [padded[i : i + order] for i in range(len(padded) - order + 1)]


def held_out(id_col: str = "doc_id") -> Column:
    return F.crc32(F.col(id_col).cast("string")) % 4 == 2


def _counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """lang, order (0: a word), item, n; summed within a batch."""
    for batch in batches:
        words: dict[str, Counter] = {}
        for text, lang in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            words.setdefault(lang, Counter()).update(_WORD.findall((text or "").lower()))
        for lang, found in words.items():
            table: Counter = Counter()
            for word, n in found.items():
                table[0, word] += n
                for order in ORDERS:
                    for gram in grams(word, order):
                        table[order, gram] += n
            keys = list(table)
            for at in range(0, len(keys), 20_000):
                part = keys[at : at + 20_000]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([lang] * len(part)), pa.array([k[0] for k in part], pa.int32()), pa.array([k[1] for k in part]), pa.array([table[k] for k in part], pa.int64())],
                    names=["lang", "kind", "item", "n"],
                )


def fit(docs: DataFrame, max_docs: int = MAX_DOCS, max_words: int = MAX_WORDS, max_grams: int = MAX_GRAMS, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> dict:
    """{"langs": [...], "logs": {(order, item): log-probabilities by language}}"""
    train = docs.filter(F.col(lang_col).isNotNull() & F.col(id_col).isNotNull() & ~held_out(id_col))
    digest = F.xxhash64(F.col(id_col).cast("long"))
    # The smallest digests without sorting texts: only ids are ranked, and the bound is that of the sample.
    edge = train.select(digest.alias("h")).orderBy("h").limit(max_docs).agg(F.max("h")).first()[0]
    if edge is None:
        return {"langs": [], "logs": {}}
    sample = train.filter(digest <= F.lit(edge)).select(F.col(text_col), F.col(lang_col))
    sums = sample.mapInArrow(tidy(_counts), "lang string, kind int, item string, n long").groupBy("lang", "kind", "item").agg(F.sum("n").alias("n"))
    sums = checkpointed(sums)
    total = {(r.lang, r.kind): r.total for r in sums.groupBy("lang", "kind").agg(F.sum("n").alias("total")).collect()}
    # The cut is found on the numbers of items by frequency, a small table, so no task ranks all items of a language: an item
    # stays if at most ``most`` items are as frequent as it, so items of one frequency stay or go together.
    most = F.when(F.col("kind") == 0, max_words).otherwise(max_grams)
    upto = F.sum("items").over(Window.partitionBy("lang", "kind").orderBy(F.desc("n")))
    cuts = sums.groupBy("lang", "kind", "n").agg(F.count(F.lit(1)).alias("items")).withColumn("upto", upto).filter(F.col("upto") <= most).groupBy("lang", "kind").agg(F.min("n").alias("least"))
    least = {(r.lang, r.kind): r.least for r in cuts.collect()}
    kept = F.lit(False)
    for (lang, kind), n in sorted(least.items()):
        kept = kept | ((F.col("lang") == lang) & (F.col("kind") == kind) & (F.col("n") >= n))
    rows = sums.filter(kept).collect()
    langs = sorted({r.lang for r in rows})
    place = {lang: i for i, lang in enumerate(langs)}
    counts: dict[tuple[int, str], np.ndarray] = {}
    for r in rows:
        counts.setdefault((r.kind, r.item), np.zeros(len(langs)))[place[r.lang]] = r.n
    size = {k: np.array([total.get((lang, k), 0) for lang in langs], float) for k in (0, *ORDERS)}
    logs = {key: np.log((n + 0.1) / (size[key[0]] + 1000.0)).astype(np.float32) for key, n in counts.items()}
    return {"langs": langs, "logs": logs}


class Scorer:
    def __init__(self, model: dict) -> None:
        self.langs, self.logs = model["langs"], model["logs"]
        self._empty()

    def _empty(self) -> None:
        self.known: dict[str, int] = {}
        self.table = np.zeros((1024, max(1, len(self.langs))), np.float32)

    def word(self, word: str) -> np.ndarray:
        row = self.logs.get((0, word))
        if row is None:
            for order in ORDERS:
                seen = [g for x in grams(word, order) if (g := self.logs.get((order, x))) is not None]
                if seen:
                    row = sum(seen) / len(seen)
                    break
            else:
                return np.zeros(len(self.langs), np.float32)
        return row - row.max()

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        names, scores = [], []
        for text in texts:
            words = _WORD.findall(text.lower()) if text else []
            if not words or not self.langs:
                names.append("und")
                scores.append(0.0)
                continue
            new = set(words).difference(self.known)
            if new:
                if len(self.known) + len(new) > KEPT_WORDS:
                    self._empty()
                    new = set(words)
                for w in new:
                    i = self.known[w] = len(self.known)
                    if i >= len(self.table):
                        self.table = np.concatenate([self.table, np.zeros_like(self.table)])
                    self.table[i] = self.word(w)
            at = np.fromiter(map(self.known.__getitem__, words), np.int64, len(words))
            total = self.table[at].sum(axis=0, dtype=np.float64) / max(1.0, len(words) ** 0.5)
            p = np.exp(total - total.max())
            best = int(p.argmax())
            names.append(self.langs[best])
            scores.append(float(p[best] / p.sum()))
        return names, scores


def _predictor(shared, all_columns: bool, text_at: int, least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(shared.value)
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                names, scores = scorer.predict(part.column(text_at).to_pylist())
                if all_columns:
                    yield part.filter(pa.array([n != "und" and s >= least for n, s in zip(names, scores, strict=True)], pa.bool_()))
                else:
                    yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(names, pa.string()), pa.array(scores, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])

    return run


def identify(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **bounds) -> DataFrame:
    """doc_id, held_out, lang_pred, score; the model is fitted on the rows that are not held out."""
    shared = docs.sparkSession.sparkContext.broadcast(fit(docs, id_col=id_col, text_col=text_col, **bounds))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(held_out(id_col), F.lit(False)).alias("held_out"), F.col(text_col).alias("text"))
    return rows.mapInArrow(tidy(_predictor(shared, False, 2, 0.0)), "doc_id long, held_out boolean, lang_pred string, score double")


def keep_identified(docs: DataFrame, least: float = 0.5, text_col: str = "text", **bounds) -> DataFrame:
    """The rows whose language is identified with a score of at least ``least``, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(fit(docs, text_col=text_col, **bounds))
    return docs.mapInArrow(tidy(_predictor(shared, True, docs.columns.index(text_col), least)), docs.schema)
