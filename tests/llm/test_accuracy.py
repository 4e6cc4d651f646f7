"""Held-out accuracy of the learned operators and recall of near-duplicate links, on the given documents."""

import zlib

import numpy as np
import pytest

from blockmatch.llm import hyperminhash, langid, quality

SF = "/root/testdata/sf0.01"


def test_language_of_held_out_documents(spark):
    got = {r["doc_id"]: r for r in langid.op4_language(spark, SF).collect()}
    docs = spark.read.parquet(f"{SF}/documents.parquet").collect()
    assert len(got) == len(docs)
    held = [r for r in docs if r["lang"] is not None and got[r["doc_id"]]["held_out"] and got[r["doc_id"]]["lang_pred"] != "und"]
    assert len(held) > 100
    assert all(got[r["doc_id"]]["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in docs)
    assert np.mean([got[r["doc_id"]]["lang_pred"] == r["lang"] for r in held]) >= 0.97


def test_filters_against_exact_sets():
    """Popcounts of the bit-sliced filters, corrected, against sets of n-grams."""
    rows = [("a", "the quick brown fox jumps over the lazy dog " * 3), ("b", "le renard brun saute par dessus le chien " * 3), ("c", "der schnelle braune fuchs springt ueber den hund " * 3)]
    model = langid.SlicedFilters.fit(rows)
    own = {lang: set(langid.grams([t])[0].tolist()) for lang, t in rows}
    for text in ("the lazy fox", "le chien saute", "der hund springt schnell", "zzz qqq xxx"):
        g, n = langid.grams([text])
        count, size = model.counts([text])
        assert size[0] == n[0] == len(g)
        for k, lang in enumerate(model.languages):
            exact = sum(x in own[lang] for x in g.tolist())
            assert exact <= count[0, k] <= exact + max(2, 0.05 * n[0])


def test_quality_of_held_out_documents(spark):
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    rows = [(r["score"], labels[r["doc_id"]]) for r in quality.op10_quality(spark, SF).collect() if r["held_out"] and r["doc_id"] in labels]
    score, label = np.array([r[0] for r in rows]), np.array([r[1] for r in rows])
    assert 10 < label.sum() < len(label)
    order = np.argsort(score)
    rank = np.empty(len(score))
    rank[order] = np.arange(1, len(score) + 1)
    auc = (rank[label == 1].sum() - label.sum() * (label.sum() + 1) / 2) / (label.sum() * (label == 0).sum())
    assert auc >= 0.97
    assert np.mean((score >= 0.5) == (label == 1)) >= 0.95
    # calibration: the mean score is near the share of good documents, and the squared error small
    assert abs(score.mean() - label.mean()) < 0.1 and np.mean((score - label) ** 2) < 0.05


@pytest.fixture(scope="module")
def sets(spark):
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()]
    return [i for i, _ in rows], hyperminhash.shingle_sets([t or "" for _, t in rows])


def test_near_duplicate_components_against_brute_force(spark, sets):
    ids, each = sets
    top = {i: i for i in ids}

    def find(a):
        while top[a] != a:
            a = top[a]
        return a

    order = sorted((k for k in range(len(ids)) if len(each[k])), key=lambda k: len(each[k]))
    links = 0
    for a, k in enumerate(order):
        for j in order[a + 1 :]:
            if 100 * len(each[k]) < 75 * len(each[j]):
                break
            both = len(np.intersect1d(each[k], each[j], assume_unique=True))
            if 100 * both >= 75 * (len(each[k]) + len(each[j]) - both):
                links += 1
                x, y = find(ids[k]), find(ids[j])
                top[max(x, y)] = min(x, y)
    got = {r["doc_id"]: r["component_id"] for r in hyperminhash.op8_near_duplicates(spark, SF).collect()}
    assert links > 20 and got == {i: find(i) for i in ids}


@pytest.mark.parametrize("size", [3, 8, 30, 100, 400, 2000])
def test_recall_of_the_bands_by_size_of_the_sets(size):
    """Pairs just above the threshold: how many share a band and pass the sketch test."""
    rng = np.random.default_rng(size)
    n, found = 400, 0
    both = -(-3 * 2 * size // 7) if size > 3 else 3  # least common shingles of two sets of that size
    for _ in range(n):
        pool = np.unique(rng.integers(0, 2**63, 3 * size).astype(np.uint64) * np.uint64(2) + rng.integers(0, 2, 3 * size).astype(np.uint64))
        pool = rng.permutation(pool)
        a, b = (np.sort(pool[:size]), np.sort(np.concatenate((pool[:both], pool[size : 2 * size - both])))) if size > 3 else (np.sort(pool[:3]), np.sort(pool[:4]))
        share = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
        assert 0.75 <= share < 0.85
        regs = hyperminhash.registers_of([a, b]).reshape(2, hyperminhash.BANDS, hyperminhash.ROWS)
        bits = sum(int(x).bit_count() for x in np.bitwise_xor(*hyperminhash.parities([a, b]).view(np.uint64)))
        d = (len(a) + len(b)) / 7
        rest = np.exp(-2 * d / hyperminhash.BITS)
        limit = hyperminhash.BITS / 2 * (1 - rest) + 6 * np.sqrt(max(hyperminhash.BITS / 4 * (1 - rest**2) - d * rest**2, 0))
        found += bool((regs[0] == regs[1]).all(axis=1).any()) and bits <= min(d + 1e-3, limit)
    assert found / n >= 0.995
