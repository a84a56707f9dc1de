"""Language identification by rank-order profiles.

A profile is the list of a text's most frequent character n-grams (n = 1..3 over lower
case letters, words bounded by a blank).  A document goes to the language whose profile
is nearest by out-of-place distance: the sum over the document's n-grams of how far their
ranks lie apart, with the profile length for n-grams the language lacks.

Profiles are learned from a bounded sample of labelled documents: at most `max_languages`
languages, those with most documents, and of each about `sample_rows` documents, those
whose hashed id falls under a threshold set by the language's number of documents.

Defined cases: a null text or one without letters is `und` with score 0; equal counts are
ranked by n-gram, equal distances go to the first language by name; repeated rows are
predicted alike; with nothing to learn from, every prediction is `und`; an empty table
gives no rows; other columns are ignored.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from subvote.llm._text import ragged, text_slices
from subvote.llm._worker import tidied

_table: dict[str, np.ndarray] = {}


def _letters() -> np.ndarray:
    """Per code point: the code point of its lower-case letter, or 0 where it is no letter."""
    if "letters" not in _table:
        out = np.zeros(sys.maxunicode + 1, np.int32)
        for c in range(sys.maxunicode + 1):
            s = chr(c)
            if s.isalpha():
                low = s.lower()
                out[c] = ord(low) if len(low) == 1 else c
        _table["letters"] = out
    return _table["letters"]


def grams_of(points: np.ndarray, n_max: int = 3) -> np.ndarray:
    """All n-grams of a text as integers: 21 bits per letter, 0 for the bound of a word."""
    low = _letters()[points]
    keep = np.ones(len(low), dtype=bool)
    keep[1:] = (low[1:] > 0) | (low[:-1] > 0)  # one bound between words
    low = low[keep].astype(np.int64)
    low = np.concatenate([[0] if len(low) and low[0] else [], low, [0] if len(low) and low[-1] else []]).astype(np.int64)
    out = [low[low > 0]]
    code = low
    for n in range(2, n_max + 1):
        code = (code[:-1] << 21) | low[n - 1 :] if len(code) > 1 else code[:0]
        inner = np.ones(len(code), dtype=bool)
        # A bigram with a leading bound must differ from its second letter alone.
        bound = np.int64(1 << 42) if n == 2 else np.int64(0)
        for j in range(1, n - 1):  # a word's bound stands at the ends only
            inner &= low[j : j + len(code)] > 0
        out.append(code[inner] | bound)
    return np.concatenate(out)


def profile(points: np.ndarray, top: int) -> np.ndarray:
    """The most frequent n-grams of a text, by falling count, then n-gram."""
    gram, count = np.unique(grams_of(points), return_counts=True)
    if len(gram) > top:
        least = np.partition(count, len(count) - top)[len(count) - top]
        keep = count >= least
        gram, count = gram[keep], count[keep]
    return gram[np.argsort(-count, kind="stable")][:top]


class Profiles:
    """Profiles of all languages as postings: per n-gram the languages that rank it, and where."""

    def __init__(self, ranked: dict[str, list[int]], top: int):
        self.names, self.top = sorted(ranked), top
        sizes = [len(ranked[n]) for n in self.names]
        gram = np.array([g for n in self.names for g in ranked[n]], np.int64)
        lang = np.repeat(np.arange(len(sizes)), sizes).astype(np.int64)
        rank = np.concatenate([np.arange(n) for n in sizes]) if sizes else np.empty(0, np.int64)
        order = np.argsort(gram, kind="stable")
        self.lang, self.rank = lang[order], rank[order]
        self.grams, first = np.unique(gram[order], return_index=True)
        self.edges = np.append(first, len(gram))

    def predict(self, points: np.ndarray) -> tuple[str, float]:
        mine = profile(points, self.top)
        if not len(mine) or not self.names:
            return "und", 0.0
        # Every n-gram costs the profile length, less what a language that ranks it saves.
        at = np.minimum(np.searchsorted(self.grams, mine), len(self.grams) - 1)
        place = np.flatnonzero(self.grams[at] == mine)
        begin, n = self.edges[at[place]], self.edges[at[place] + 1] - self.edges[at[place]]
        slot = np.repeat(begin, n) + ragged(n)
        saved = self.top - np.minimum(np.abs(self.rank[slot] - np.repeat(place, n)), self.top)
        distance = self.top * len(mine) - np.bincount(self.lang[slot], weights=saved, minlength=len(self.names))
        best = int(np.argmin(distance))
        return self.names[best], 1.0 - float(distance[best]) / (self.top * len(mine))


def fit(
    docs: DataFrame, labelled: str, sample_rows: int = 2000, top: int = 300, max_languages: int = 5000, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang"
) -> Profiles:
    """Learn profiles from the rows for which the SQL predicate `labelled` holds."""
    rows = docs.filter(labelled).filter(F.col(lang_col).isNotNull() & F.col(id_col).isNotNull())
    counts = rows.groupBy(F.col(lang_col).alias("k_lang")).agg(F.count("*").alias("k_n"))
    counts = counts.orderBy(F.desc("k_n"), "k_lang").limit(max_languages).collect()
    known = F.broadcast(docs.sparkSession.createDataFrame(counts, "k_lang string, k_n long"))  # max_languages rows
    drawn = F.pmod(F.xxhash64(F.col("id")), F.lit(1 << 40)).cast("double") * F.col("k_n") < F.lit(sample_rows * float(1 << 40))
    rows = rows.select(F.col(id_col).alias("id"), F.col(lang_col).alias("lang"), F.col(text_col).alias("text"))
    sample = rows.join(known, F.col("lang") == F.col("k_lang")).filter(drawn).select("k_lang", "text")

    @tidied
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            langs, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for lang in sorted(set(langs)):
                found = [grams_of(_points(t)) for t, x in zip(texts, langs, strict=True) if x == lang and t]
                if found:
                    gram, n = np.unique(np.concatenate(found), return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array([lang] * len(gram)), pa.array(gram), pa.array(n)], ["lang", "gram", "n"])

    counts = sample.mapInArrow(count, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    place = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "gram"))
    best = counts.withColumn("place", place).filter(F.col("place") <= top)
    ranked: dict[str, list[int]] = {}
    for r in sorted(best.collect(), key=lambda r: (r["lang"], r["place"])):  # at most top rows per language
        ranked.setdefault(r["lang"], []).append(r["gram"])
    return Profiles(ranked, top)


def _points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le"), np.uint32)


def predict(docs: DataFrame, profiles: Profiles, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, lang_pred, score of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(profiles)  # languages times `top` entries

    @tidied
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            for lo, hi, buf, offs in text_slices(batch.column(1)):
                raw = buf.tobytes()
                found = [model.predict(_points(raw[a:b].decode())) for a, b in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(lo, hi - lo), pa.array([f[0] for f in found]), pa.array([f[1] for f in found])], ["doc_id", "lang_pred", "score"]
                )

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), text_col).mapInArrow(run, "doc_id long, lang_pred string, score double")
