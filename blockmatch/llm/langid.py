"""Language ID by bit-sliced Bloom filters of character n-grams.

All languages share one table: a slot holds one bit a language, and and-ing an n-gram's
slots gives at once the mask of the languages whose filter contains it. A document's
per-language popcounts, corrected for each filter's false positives, decide.

Fitting reads the whole texts of a bounded sample of documents of each known language; the filters' size is a
parameter, so what is sent to the tasks doesn't grow with the corpus. Prediction reads
every whole text, in blocks.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import blocks, documents, fold, mix, schema

GRAM = 4
#: Bound of the fitting sample: documents of each language, with their whole texts.
SAMPLE_DOCS = 2000
SLOTS, PROBES = 1 << 20, 4
#: An n-gram is kept for a language in whose documents it is this frequent, absolutely and against its best language.
MIN_SHARE, MIN_RATIO = 0.02, 0.2
_LETTER = re.compile(r"[^\W\d_]")


def grams(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all n-grams and their number in each text; anything but letters is one boundary sign."""
    codes = [np.frombuffer(f" {t.lower()} ".encode("utf-32-le", "surrogatepass"), np.uint32) for t in texts]
    n = np.array([max(len(c) - GRAM + 1, 0) for c in codes])
    code = np.concatenate(codes) if codes else np.zeros(0, np.uint32)
    code = np.where((code < 128) & ~((code >= 97) & (code <= 122)), 32, code).astype(np.uint64)
    whole = np.zeros(max(len(code) - GRAM + 1, 0), np.uint64)
    for k in range(GRAM):
        whole = whole * np.uint64(0x100000001B3) + code[k : len(code) - GRAM + 1 + k]
    size = np.array([len(c) for c in codes])
    inside = np.ones(len(whole), bool)
    for end in np.cumsum(size)[:-1]:
        inside[max(end - GRAM + 1, 0) : end] = False
    return mix(whole[inside]), n


@dataclass
class SlicedFilters:
    languages: list[str]
    table: np.ndarray  # one row for each 64 languages, one column a slot
    false_rate: np.ndarray

    @classmethod
    def fit(cls, rows: list[tuple[str, str]]) -> SlicedFilters:
        """From (language, text) pairs."""
        languages = sorted({r[0] for r in rows})
        seen: list[dict] = []
        for lang in languages:
            texts = [t for x, t in rows if x == lang]
            each = [np.unique(grams([t])[0]) for t in texts]
            value, count = np.unique(np.concatenate(each), return_counts=True)
            seen.append((value, count / len(texts)))
        value = np.unique(np.concatenate([v for v, _ in seen])) if seen else np.zeros(0, np.uint64)
        share = np.zeros((len(languages), len(value)))
        for k, (v, s) in enumerate(seen):
            share[k, np.searchsorted(value, v)] = s
        best = share.max(axis=0, initial=0)
        kind = np.uint8 if len(languages) <= 8 else np.uint64
        table = np.zeros((max(1, -(-len(languages) // 64)), SLOTS), kind)
        rate = np.zeros(len(languages))
        for k in range(len(languages)):
            own = value[(share[k] >= MIN_SHARE) & (share[k] >= MIN_RATIO * best)]
            bit = kind(1 << (k % 64))
            for at in cls.slots(own):
                table[k // 64, at] |= bit
            rate[k] = np.mean(table[k // 64] & bit != 0) ** PROBES
        return cls(languages, table, rate)

    @staticmethod
    def slots(h: np.ndarray) -> list[np.ndarray]:
        step = (h >> np.uint64(40)) | np.uint64(1)
        return [((h + np.uint64(i) * step) & np.uint64(SLOTS - 1)).astype(np.int64) for i in range(PROBES)]

    def counts(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Popcount of each language (rows: texts) and number of n-grams."""
        h, n = grams(texts)
        at = self.slots(h)
        out = np.zeros((len(texts), len(self.languages)), np.int64)
        ends = np.concatenate(([0], np.cumsum(n)))
        for w, row in enumerate(self.table):
            mask = row[at[0]] & row[at[1]]
            for a in at[2:]:
                mask &= row[a]
            for k in range(64 * w, min(64 * (w + 1), len(self.languages))):
                hits = np.concatenate(([0], np.cumsum((mask >> mask.dtype.type(k % 64)) & mask.dtype.type(1), dtype=np.int64)))
                out[:, k] = hits[ends[1:]] - hits[ends[:-1]]
        return out, n

    def decide(self, count: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Best language (ties: first by name) and its share of the corrected counts."""
        fair = ((count - n[:, None] * self.false_rate) / (1 - self.false_rate)).clip(0)
        total = fair.sum(axis=1)
        best = fair.argmax(axis=1)
        return best, np.where(total > 0, fair[np.arange(len(fair)), best] / np.where(total > 0, total, 1), 0.0)


def sample_rows(docs: DataFrame, learn: F.Column, most: int = SAMPLE_DOCS) -> DataFrame:
    """A bounded sample: of each language the documents with the smallest hash among those that may be learned from."""
    rows = docs.filter(learn).select("lang", F.col("doc_id").alias("_id"), F.xxhash64("doc_id", F.lit(17)).alias("_hash")).distinct()
    size = rows.groupBy("lang").agg(F.count("*").alias("_n"))
    # a language's share of hashes that holds its `most` smallest by ten standard deviations, so that its window stays small
    near = F.col("_hash") / 2.0**64 + 0.5 <= (most + 10 * most**0.5) / F.col("_n")
    place = F.row_number().over(W.partitionBy("lang").orderBy("_hash", "_id"))
    ids = rows.join(F.broadcast(size), "lang").filter(near).withColumn("_place", place).filter(F.col("_place") <= most).select("_id")
    return docs.join(F.broadcast(ids.distinct()), F.col("doc_id") == F.col("_id"), "left_semi").filter(learn)


def fit_languages(docs: DataFrame, learn: F.Column) -> SlicedFilters:
    learn = learn & F.col("lang").isNotNull() & F.col("text").isNotNull()
    rows = sample_rows(docs, learn).groupBy("doc_id", "lang").agg(F.min("text").alias("text"))
    return SlicedFilters.fit([(r["lang"], r["text"]) for r in rows.collect()])


def predict_languages(docs: DataFrame, model: SlicedFilters) -> DataFrame:
    """doc_id, held_out as given, lang_pred, score; `und` and 0 for null texts and texts without a letter."""
    out = schema(doc_id="long", held_out="boolean", lang_pred="string", score="double")
    sent = docs.sparkSession.sparkContext.broadcast(model)
    block = 1_000_000

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        for batch in batches:
            ids, fold_, texts = batch.column(0), batch.column(1), batch.column(2).to_pylist()
            for part in blocks(texts, [len(t or "") for t in texts], block):
                some = [t or "" for t in texts[part]]
                if len(some) == 1 and len(some[0]) > block:  # a very long text: overlapping blocks
                    cuts = [some[0][max(0, i - GRAM + 1) : i + block] for i in range(0, len(some[0]), block)]
                    both = [m.counts([c]) for c in cuts]
                    count, n = sum(b[0] for b in both), sum(b[1] for b in both)
                else:
                    count, n = m.counts(some)
                best, score = m.decide(count, n) if m.languages else (np.zeros(len(some), int), np.zeros(len(some)))
                letter = [bool(m.languages) and bool(_LETTER.search(t)) for t in some]
                lang = [m.languages[b] if x else "und" for b, x in zip(best, letter)]
                k = part.stop - part.start
                yield pa.RecordBatch.from_arrays([ids.slice(part.start, k), fold_.slice(part.start, k), pa.array(lang, pa.string()), pa.array(np.where(letter, score, 0.0))], names=out.names)

    return docs.select("doc_id", "held_out", "text").mapInArrow(run, out)


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Learn from the documents outside the held-out fifth; predict all. Repeated rows are predicted each; an empty table gives no rows."""
    docs = documents(spark, sf_dir).select("doc_id", "text", "lang").withColumn("held_out", fold(F.col("doc_id"), 5) == 0)
    return predict_languages(docs, fit_languages(docs, ~F.col("held_out")))
