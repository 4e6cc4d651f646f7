"""Quality classifier: random-indexing word vectors, pooled, and a two-layer network.

Every word gives up to three tokens: the bare lower-case word, its shape (case and tail
signs), and a sign when it repeats the word before. A token's vector is the sum of the
sparse random index vectors of the tokens near it over the sample, centred and scaled. A
document's vector is the mean over its tokens; a two-layer network in numpy gives a
probability, whose temperature is set on a part of the sample left out of training.

Fitting reads the whole texts of a bounded sample of labelled documents. Scoring reads every whole text; the
first layer is folded into the token table, so a word costs one look-up.
"""

from __future__ import annotations

import string
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import blocks, documents, fold, schema, text_or_empty, tidy

#: Bound of the fitting sample: labelled documents, each with its whole text.
SAMPLE_DOCS = 3000
#: Tokens with a vector (the most frequent of the sample), dimensions, hidden units, signs in an index vector.
VOCABULARY, DIMS, HIDDEN, SIGNS = 20_000, 64, 16, 6
THRESHOLD = 0.7
SAME = "\0same"
#: Words that a worker remembers; beyond it the table starts anew.
REMEMBER = 50_000
#: Characters of text that a task scores at once.
BLOCK = 500_000


def tokens_of(word: str) -> tuple[str, str]:
    """The bare word and the shape."""
    core = word.rstrip(string.punctuation)
    tail = word[len(core) :]
    if not core:
        kind = "-"
    elif core.islower():
        kind = "a"
    elif core.isupper() and len(core) > 1:
        kind = "A"
    elif core.istitle() or core.isupper():
        kind = "Aa"
    else:
        kind = "1" if any(c.isdigit() for c in core) else "?"
    return core.lower(), f"\0{kind}{tail[:3]}"


@dataclass
class Model:
    names: dict[str, int]
    first: np.ndarray  # tokens' vectors through the first layer, one row a token, the last row zero
    bias: np.ndarray
    second: np.ndarray
    temperature: float

    def __post_init__(self):
        self.forget()

    def forget(self) -> None:
        """Drop the words this worker remembers, and what Arrow keeps for reuse: workers live on in later stages."""
        self._words: dict[str, int] = {}
        self._pairs: list[tuple[int, int]] = []
        pa.default_memory_pool().release_unused()

    def _rows(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Number of each word in this worker's table, words of each text, and the table's token rows."""
        if len(self._words) > REMEMBER:
            self._words, self._pairs = {}, []
        none, words, pairs, rows, n = len(self.first) - 1, self._words, self._pairs, [], []
        for text in texts:
            row = text.split()
            for w in set(row):
                if w not in words:
                    words[w] = len(pairs)
                    core, shape = tokens_of(w)
                    pairs.append((self.names.get(core, none), self.names.get(shape, none)))
            rows += map(words.__getitem__, row)
            n.append(len(row))
        return np.array(rows, np.int64), np.array(n, np.int64), np.array(pairs, np.int64).reshape(-1, 2)

    def pooled(self, texts: list[str]) -> np.ndarray:
        """Mean over a text's tokens of their rows of `first`."""
        word, n, pairs = self._rows(texts)
        ends = np.concatenate(([0], np.cumsum(n)))
        doc = np.repeat(np.arange(len(n)), n)
        same = np.zeros(len(word), bool)
        same[1:] = (word[1:] == word[:-1]) & (doc[1:] == doc[:-1])
        used = pairs[word]
        none = len(self.first) - 1
        each = self.first[used[:, 0]] + self.first[used[:, 1]]
        sums = np.concatenate((np.zeros((1, each.shape[1])), np.cumsum(each, axis=0, dtype=np.float64)))
        total = sums[ends[1:]] - sums[ends[:-1]]
        count = np.concatenate(([0], np.cumsum((used != none).sum(axis=1))))
        count = (count[ends[1:]] - count[ends[:-1]]).astype(np.float64)
        if (k := self.names.get(SAME)) is not None:
            again = np.bincount(doc[same], minlength=len(n)).astype(np.float64)
            total += again[:, None] * self.first[k]
            count += again
        return total / np.maximum(count, 1)[:, None]

    def score(self, texts: list[str]) -> np.ndarray:
        hidden = np.tanh(self.pooled(texts) + self.bias)
        return 1 / (1 + np.exp(-np.clip((hidden @ self.second[:-1] + self.second[-1]) / self.temperature, -30, 30)))


def word_vectors(texts: list[str], seed: int = 11) -> tuple[dict[str, int], np.ndarray]:
    """Random indexing over the texts: token numbers and their vectors."""
    def stream(text: str) -> Iterator[list[str]]:
        last = None
        for w in text.split():
            yield [*tokens_of(w), *([SAME] if w == last else [])]
            last = w

    count: Counter = Counter()
    for text in texts:  # two passes, so that one text's tokens are held at a time
        count.update(t for row in stream(text) for t in row if t)
    names = {t: k for k, (t, _) in enumerate(sorted(count.items(), key=lambda x: (-x[1], x[0]))[:VOCABULARY])}
    rng = np.random.default_rng(seed)
    index = np.zeros((len(names), DIMS), np.float32)
    for row in index:
        row[rng.choice(DIMS, SIGNS, replace=False)] = rng.choice((-1.0, 1.0), SIGNS)
    vectors = index * 4
    for text in texts:
        slot, token, n = [], [], 0
        for i, row in enumerate(stream(text)):
            n = i + 1
            for t in row:
                if t in names:
                    slot.append(i)
                    token.append(names[t])
        if not token:
            continue
        slot, token = np.array(slot), np.array(token)
        sums = np.zeros((n + 4, DIMS), np.float32)
        np.add.at(sums, slot + 2, index[token])
        around = sums[:-4] + sums[1:-3] + sums[2:-2] + sums[3:-1] + sums[4:]
        np.add.at(vectors, token, around[slot] / 5)
    vectors /= np.linalg.norm(vectors, axis=1, keepdims=True) + 1e-9
    weight = np.array([count[t] for t in names], np.float64)
    if len(names):
        vectors = vectors - (weight @ vectors / weight.sum()).astype(np.float32)
    return names, vectors


def fit_quality(rows: list[tuple[str, int]], seed: int = 5) -> Model:
    """From (text, label) pairs; a tenth sets the temperature. Without both labels the score is their share."""
    texts, label = [r[0] for r in rows], np.array([r[1] for r in rows], np.float64)
    names, vectors = word_vectors(texts)
    if len(set(label.tolist())) < 2:
        share = float(label.mean()) if len(label) else 0.5
        odds = np.log((share + 0.01) / (1.01 - share))
        return Model(names, np.zeros((len(names) + 1, HIDDEN), np.float32), np.zeros(HIDDEN), np.array([0.0] * HIDDEN + [odds]), 1.0)
    plain = Model(names, np.vstack((vectors, np.zeros((1, DIMS), np.float32))), np.zeros(DIMS), np.zeros(DIMS + 1), 1.0)
    x = np.concatenate([plain.pooled(texts[part]) for part in blocks(texts, [len(t) for t in texts], 200_000)])
    scale = x.std(axis=0) + 1e-6
    mean = x.mean(axis=0)
    z = (x - mean) / scale
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(z))
    held, train = order[: len(z) // 10], order[len(z) // 10 :]
    w = [rng.normal(0, DIMS**-0.5, (DIMS, HIDDEN)), np.zeros(HIDDEN), rng.normal(0, HIDDEN**-0.5, HIDDEN), np.zeros(1)]
    m, v = [np.zeros_like(a) for a in w], [np.zeros_like(a) for a in w]
    part = {y: max(1, (label[train] == y).sum()) for y in (0.0, 1.0)}
    weigh = np.where(label == 1, 1.0, min(4.0, part[1.0] / part[0.0]))
    step = 0
    for _ in range(60):
        rng.shuffle(train)
        for i in range(0, len(train), 64):
            b = train[i : i + 64]
            h = np.tanh(z[b] @ w[0] + w[1])
            p = 1 / (1 + np.exp(-np.clip(h @ w[2] + w[3], -30, 30)))
            g = (p - label[b]) * weigh[b] / len(b)
            back = np.outer(g, w[2]) * (1 - h * h)
            grads = [z[b].T @ back + 1e-4 * w[0], back.sum(0), h.T @ g + 1e-4 * w[2], g.sum(keepdims=True)]
            step += 1
            for k, d in enumerate(grads):
                m[k] = 0.9 * m[k] + 0.1 * d
                v[k] = 0.999 * v[k] + 0.001 * d * d
                w[k] = w[k] - 0.003 * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
    logit = np.tanh(z[held] @ w[0] + w[1]) @ w[2] + w[3]
    sign = np.where(label[held] == 1, 1.0, -1.0)
    grid = np.geomspace(0.5, 4, 25)
    loss = [np.logaddexp(0, -sign * logit / t).mean() if len(held) else 0.0 for t in grid]
    folded = w[0] / scale[:, None]
    first = np.vstack((vectors @ folded, np.zeros((1, HIDDEN)))).astype(np.float32)
    return Model(names, first, w[1] - mean @ folded, np.concatenate((w[2], w[3])), float(grid[int(np.argmin(loss))]))


def fit_from(docs: DataFrame, labels: DataFrame, learn: F.Column) -> Model:
    """Fit on the labelled documents of `learn` with the smallest hash of their id, SAMPLE_DOCS at most."""
    labels = labels.filter("quality is not null").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    ids = labels.filter(learn).orderBy(F.xxhash64("doc_id", F.lit(23)), "doc_id").limit(SAMPLE_DOCS).select(F.col("doc_id").alias("_id"), "quality")
    rows = docs.select("doc_id", text_or_empty().alias("text")).join(F.broadcast(ids), F.col("doc_id") == F.col("_id"))
    rows = rows.groupBy("doc_id", "quality").agg(F.min("text").alias("text")).collect()  # of repeated rows one
    return fit_quality([(r["text"], r["quality"]) for r in sorted(rows, key=lambda r: (r["doc_id"], r["text"]))])


def score_documents(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id and score of every row; null text counts as empty."""
    out = schema(doc_id="long", score="double")
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1).to_pylist()
            for part in blocks(texts, [len(t) for t in texts], BLOCK):
                score = sent.value.score(texts[part])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(part.start, len(score)), pa.array(score)], names=out.names)
        sent.value.forget()

    return docs.select("doc_id", text_or_empty().alias("text")).mapInArrow(tidy(run), out)


def keep_quality(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """The documents whose score reaches the threshold; columns as given."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [t or "" for t in batch.column(batch.schema.get_field_index("text")).to_pylist()]
            score = [sent.value.score(texts[part]) for part in blocks(texts, [len(t) for t in texts], BLOCK)]
            if texts:
                yield batch.filter(pa.array(np.concatenate(score) >= threshold))
        sent.value.forget()

    return docs.mapInArrow(tidy(run), docs.schema)


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Learn from labelled rows outside the held-out quarter; score all.

    Repeated and equal texts score alike; null counts as empty, an empty text has a score,
    too; very long texts are scored alone, whole. A document with several labels counts with
    the largest. An empty table gives no rows. Other columns aren't read.
    """
    docs, labels = documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = fit_from(docs, labels, fold(F.col("doc_id"), 4) != 2)
    rows = score_documents(docs, model)
    return rows.select("doc_id", (fold(F.col("doc_id"), 4) == 2).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
