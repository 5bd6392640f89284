"""Language identification with rank-order n-gram profiles.

A profile is the list of a language's most frequent letter n-grams (1 to 3, words padded with a blank on both sides).
A document gets the language whose profile has the smallest out-of-place distance to the document's own list:
the sum of rank differences, with a fixed penalty for n-grams that the profile lacks.

Edge cases: null texts and texts without a letter give `und` and score 0; ties go to the first language in code
point order; repeated rows get equal results; with no learnable row every document is `und`; further columns pass.
Profiles are learned from at most about `DOCS_PER_LANG` documents of each language, chosen by a hash of their text.
"""

from __future__ import annotations

import re
import unicodedata
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import textscan as ts

TOP = 300
ORDERS = (1, 2, 3)
#: Bound of the learning sample: expected number of documents for each language.
DOCS_PER_LANG = 3000
GRAM_CAP = 1 << 17
WORD_CAP = 1 << 19
#: Word characters that are numerals, not letters (all lie in the first two planes).
_NUMERALS = "".join(chr(i) for i in range(0x20000) if unicodedata.category(chr(i)) in ("No", "Nl"))
LETTERS = re.compile(rf"[^\W\d_{_NUMERALS}]+")
_LETTERS_OR_NUMERALS = re.compile(r"[^\W\d_]+")


def grams(word: str) -> list[str]:
    padded = f" {word} "
    return [g for n in ORDERS for i in range(len(padded) - n + 1) if (g := padded[i : i + n]) != " "]


def words(text: str) -> list[str]:
    """Runs of letters in lower case: what LETTERS finds, whose long class is only tried on runs that have a numeral."""
    found = _LETTERS_OR_NUMERALS.findall(text.lower())
    if all(map(str.isalpha, found)):
        return found
    return [w for run in found for w in ((run,) if run.isalpha() else LETTERS.findall(run))]


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    counts: dict[str, Counter] = {}
    for batch in batches:
        for lang, text in zip(batch.column("lang").to_pylist(), batch.column("text").to_pylist(), strict=True):
            counts.setdefault(lang, Counter()).update(words(text or ""))
    for lang, counter in counts.items():
        out: Counter = Counter()
        for w, n in counter.items():
            for g in grams(w):
                out[g] += n
        yield pa.RecordBatch.from_pydict({"lang": [lang] * len(out), "gram": list(out), "n": pa.array(out.values(), pa.int64())})


def learn(df: DataFrame, may_learn: Column, top: int = TOP, docs_per_lang: int = DOCS_PER_LANG) -> dict[str, list[str]]:
    """Profiles by language, from rows with a language for which may_learn holds."""
    rows = df.filter(may_learn & F.col("lang").isNotNull() & F.col("text").isNotNull())
    sizes = rows.groupBy("lang").count().collect()  # one row a language
    share = F.lit(0.0)
    for lang, n in sizes:
        share = F.when(F.col("lang") == lang, min(1.0, docs_per_lang / n)).otherwise(share)
    pick = (F.pmod(F.xxhash64("text"), F.lit(1 << 20)) / float(1 << 20)) < share
    sample = rows.filter(pick).select("lang", "text")
    counted = sample.transform(ts.mapped, _count, "lang string, gram string, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    order = Window.partitionBy("lang").orderBy(F.desc("n"), "gram")
    best = counted.withColumn("r", F.row_number().over(order)).filter(F.col("r") <= top).select("lang", "r", "gram").collect()
    out: dict[str, list[str]] = {}
    for lang, _, gram in sorted(best):
        out.setdefault(lang, []).append(gram)
    return out


class Identifier:
    def __init__(self, profiles: dict[str, list[str]], top: int = TOP) -> None:
        self.langs, self.profiles, self.top = sorted(profiles), profiles, top
        self._reset()

    def _reset(self) -> None:
        self.ids: dict[str, int] = {}
        self.words: dict[str, np.ndarray] = {}
        self.keys = np.zeros(1024, np.uint64)
        self.ranks = np.full((len(self.langs), 1024), -1, np.int32)
        for i, lang in enumerate(self.langs):
            for r, g in enumerate(self.profiles[lang]):
                k = self._id(g)  # may enlarge ranks
                self.ranks[i, k] = r

    def _id(self, gram: str) -> int:
        k = self.ids.get(gram)
        if k is None:
            k = self.ids[gram] = len(self.ids)
            if k >= len(self.keys):
                self.keys = np.concatenate([self.keys, np.zeros_like(self.keys)])
                self.ranks = np.concatenate([self.ranks, np.full_like(self.ranks, -1)], axis=1)
            self.keys[k] = xxhash.xxh64_intdigest(gram)
        return k

    def _of(self, word: str) -> np.ndarray:
        a = self.words[word] = np.fromiter((self._id(g) for g in grams(word)), np.int32)
        return a

    def predict(self, text: str | None) -> tuple[str, float]:
        counted = Counter(words(text)) if text else None
        if not counted or not self.langs:
            return "und", 0.0
        if len(self.ids) > GRAM_CAP or len(self.words) > WORD_CAP:
            self._reset()
        known = self.words
        parts = [known[w] if w in known else self._of(w) for w in counted]
        sizes = np.fromiter(map(len, parts), np.int64, len(parts))
        counts = np.bincount(np.concatenate(parts), weights=np.repeat(np.fromiter(counted.values(), float, len(parts)), sizes))
        seen = np.flatnonzero(counts)
        order = np.lexsort((self.keys[seen], -counts[seen]))[: self.top]
        ranks = self.ranks[:, seen[order]]
        apart = np.where(ranks >= 0, np.abs(ranks - np.arange(len(order))), self.top).sum(1)
        best = int(apart.argmin())
        return self.langs[best], 1.0 - float(apart[best]) / (self.top * len(order))


def identify(df: DataFrame, profiles: dict[str, list[str]], top: int = TOP) -> DataFrame:
    """df's doc_id with lang_pred and score; texts are read whole."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = Identifier(profiles, top)
        for batch in batches:
            got = [model.predict(t.as_py()) for t in batch.column("text")]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([x[0] for x in got], pa.string()), pa.array([x[1] for x in got], pa.float64())], ["doc_id", "lang_pred", "score"])

    return df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).transform(ts.mapped, run, "doc_id long, lang_pred string, score double")
