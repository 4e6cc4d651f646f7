"""Equality of words, windows and shingles is that of their text; no structured pair of texts hashes alike."""

import random

import numpy as np
import pytest

from blockmatch.llm import hyperminhash, substrings
from blockmatch.llm.common import window_codes, word_codes, word_spans

from test_operators import brute_components, brute_windows


def thue_morse(n, a="a", b="b"):
    return "".join(b if bin(i).count("1") % 2 else a for i in range(n))


LEFT, RIGHT = thue_morse(1024), thue_morse(1024, "b", "a")


def test_codes_of_words_and_windows():
    r = random.Random(1)
    words = [bytes(r.choices(b"ab", k=r.randint(1, 30))) for _ in range(20000)] + [LEFT.encode(), RIGHT.encode()]
    buffer = np.frombuffer(b" ".join(words), np.uint8)
    starts, ends = word_spans(buffer)
    one, two = (word_codes(buffer, starts, ends, salt) for salt in (0, 1))
    assert len(set(one.tolist())) == len(set(two.tolist())) == len(set(words))
    for k in (1, 2, 3, 5, 8, 13):
        code, text = window_codes(one, k).tolist(), [tuple(words[i : i + k]) for i in range(len(words) - k + 1)]
        assert len(code) == len(text) and len(set(code)) == len(set(text)) == len(set(zip(code, text)))
    assert all(len(window_codes(one[:n], k)) == max(n - k + 1, 0) for n in range(6) for k in (1, 3, 5, 13))
    signs = np.frombuffer(" ".join(LEFT + RIGHT).encode(), np.uint8)  # words in that order, too
    code = window_codes(word_codes(signs, *word_spans(signs)), 1024)
    assert code[0] != code[-1]


def test_substrings_of_a_structured_pair(spark):
    common = [f"w{i}" for i in range(12)]
    data = [(1, " ".join([*common, LEFT])), (2, " ".join([*common, RIGHT])), (3, " ".join(LEFT)), (4, " ".join(RIGHT))]
    got = substrings.dedup_substrings(spark.createDataFrame(data, "doc_id long, text string"))
    assert sorted(map(tuple, got.collect())) == brute_windows(data)


def test_near_duplicates_of_a_structured_pair(spark):
    data = [(1, LEFT), (2, RIGHT), (3, " ".join(LEFT)), (4, " ".join(RIGHT)), (5, LEFT), (6, "a b"), (7, "a b c d"), (8, "A b")]
    got = hyperminhash.near_duplicates(spark.createDataFrame(data, "doc_id long, text string")).collect()
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == brute_components(data)


@pytest.mark.parametrize("weak", [False, True])
def test_smallest_ids_with_codes_that_collide(weak, monkeypatch):
    monkeypatch.setattr(substrings, "COMPARED", 50)
    r = random.Random(2)
    strings, least, flat = [], [], []
    for _ in range(7):
        rows = [[r.choice("ab") for _ in range(r.randint(4, 9))] for _ in range(r.randint(1, 30))]
        ids = [r.randrange(100) for _ in rows]
        strings.append(np.frombuffer(b"\xff".join(" ".join(x).encode() for x in rows), np.uint8))
        least.append(np.array(ids))
        flat += [(tuple(x[k : k + 4]), i) for x, i in zip(rows, ids) for k in range(len(x) - 3)]
    coded = (lambda buffer, starts, ends: (ends - starts).astype(np.uint64)) if weak else word_codes
    ids, smallest, sizes = substrings.smallest_ids(strings, least, 4, coded)
    want = {w: min(i for v, i in flat if v == w) for w, _ in flat}
    assert ids.tolist() == [i for _, i in flat] and smallest.tolist() == [want[w] for w, _ in flat] and sizes.sum() == len(flat)


def test_substrings_split_the_bucket_of_a_common_minimiser(spark):
    """One phrase stands in nearly all windows, so they share a minimiser's bucket."""
    r = random.Random(5)
    data = [(i, " ".join(x for _ in range(r.randint(1, 6)) for x in ["all", "same", "words", *r.choices("abcd", k=5)])) for i in range(80)]
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(3)
    split = substrings.crowded(substrings.chunks(df, 400), 4, 13, 3, 20)
    assert split.hot and all(parts > 1 for _, parts in split.hot.values())
    got = substrings.dedup_substrings(df, chunk_bytes=400, bucket_words=20)
    assert sorted(map(tuple, got.collect())) == brute_windows(data)


def test_near_duplicates_deal_large_buckets_anew(spark, monkeypatch):
    """Documents of one template that don't link, with linked pairs among them; every bucket counts as large."""
    monkeypatch.setattr(hyperminhash, "HUBS", (1, 1, 1, 2))
    r = random.Random(8)
    base = [f"t{k}" for k in range(60)]
    data = [(i, " ".join(base + [f"d{i}x{k}" for k in range(24)])) for i in range(40)]
    for k, i in enumerate(r.sample(range(40), 8)):
        words = data[i][1].split()
        words[70] = "changed"
        data.append((100 + k, " ".join(words)))
    got = hyperminhash.near_duplicates(spark.createDataFrame(data, "doc_id long, text string").repartition(3), large=2).collect()
    assert {x["doc_id"]: (x["n_shingles"], x["component_id"]) for x in got} == brute_components(data)
