"""The pipeline's stages, each on the rows that the one before kept, against brute force on a small table."""

import collections
import zlib

import corpus_pipeline
import numpy as np
import pytest
from test_operators import brute_components, find_all

from blockmatch.llm import lines, mixing, packing, quality
from blockmatch.llm.tokens import PieceEncoder

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def steps(spark):
    """The rows before and behind each stage."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    # awkward rows: nulls in every column, empty and very long texts, a repeated row
    more = [(900001, None, None, None, None), (900002, "", "en", "s", 0), (900003, "word " * 30000, None, None, None), (900004, " \n\t", "de", "s", 4)]
    docs = docs.unionByName(spark.createDataFrame(more, docs.schema)).unionByName(docs.limit(1))
    out, names = {}, docs.columns
    for name, stage in corpus_pipeline.STAGES:
        before, docs = docs, stage(spark, docs, SF).persist()
        out[name] = (before.collect(), docs.collect())
        assert name == "pack" or docs.columns == names
    return out


def test_names(steps):
    assert list(steps) == ["quality", "lines", "near_duplicates", "mix", "pack"]


def test_quality_keeps_what_the_model_accepts(spark, steps):
    before, after = steps["quality"]
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    learn = quality.fold(quality.F.col("doc_id"), 4) != 2
    model = quality.fit_from(spark.createDataFrame(before, docs.schema), labels, learn)
    score = model.score([r["text"] or "" for r in before])
    assert collections.Counter(r["doc_id"] for r in after) == collections.Counter(r["doc_id"] for r, s in zip(before, score) if s >= quality.THRESHOLD)
    # clean documents stay: labelled ones that weren't learned
    true = {r["doc_id"]: r["quality"] for r in labels.collect() if zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2}
    kept = {r["doc_id"] for r in after}
    good = [i for i, y in true.items() if y == 1]
    assert good and np.mean([i in kept for i in good]) >= 0.9 and all(i not in kept for i, y in true.items() if y == 0)


def test_lines_stage(steps):
    before, after = steps["lines"]
    sites, first = collections.defaultdict(set), {}
    for r in before:
        for x in (r["text"] or "").split("\n"):
            if bare := x.strip(lines.BLANKS):
                sites[bare].add(r["source"])
                first[bare] = min(first.get(bare, r["doc_id"]), r["doc_id"])
    common = {b for b, s in sites.items() if len(s) >= lines.MIN_SITES}
    want = []
    for r in before:
        text = r["text"]
        if text is not None:
            text = "\n".join(x for x in text.split("\n") if not ((b := x.strip(lines.BLANKS)) in common and first[b] != r["doc_id"]))
        if find_all(text) or not find_all(r["text"]):
            want.append((r["doc_id"], text))
    assert sorted(((r["doc_id"], r["text"]) for r in after), key=str) == sorted(want, key=str)
    assert all(r["n_chars"] == len(r["text"]) for r in after if r["text"] is not None)


def test_near_duplicates_stage(steps):
    before, after = steps["near_duplicates"]
    comp = brute_components([(r["doc_id"], r["text"]) for r in before])
    want = {i for i, (_, c) in comp.items() if c == i}
    assert {r["doc_id"] for r in after} == want and len(want) < len(comp)


def test_mix_stage(spark, steps):
    before, after = steps["mix"]
    docs = spark.createDataFrame(before, spark.read.parquet(f"{SF}/documents.parquet").schema)
    table = {r["doc_id"]: r for r in mixing.mix_table(docs).collect()}
    times = collections.Counter(r["doc_id"] for r in after)
    once = collections.Counter(r["doc_id"] for r in before)
    for i, r in table.items():
        assert r["size"] * times[i] == r["taken"] * once[i] and times[i] <= 2 * once[i]
    size = collections.Counter()
    for r in before:
        size[r["source"]] += len(find_all(r["text"]))
    # targets by water-filling, source by source
    order = sorted((s for s in size if s is not None)) + ([None] if None in size else [])
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}
    target, total, open_ = {}, 1.5 * sum(size.values()), set(order)
    while open_:
        level = (total - sum(target.values())) / sum(weight[s] for s in open_)
        full = {s for s in open_ if weight[s] * level > 2 * size[s]}
        target |= {s: 2.0 * size[s] for s in full}
        open_ -= full
        if not full:
            target |= {s: weight[s] * level for s in open_}
            break
    taken = collections.Counter()
    for r in after:
        taken[r["source"]] += len(find_all(r["text"]))
    largest = max(len(find_all(r["text"])) for r in before)
    for s in order:
        assert abs(next(table[r["doc_id"]]["target"] for r in before if r["source"] == s) - target[s]) < 1e-3
        assert abs(taken[s] - target[s]) <= 0.25 * target[s] + largest


def test_pack_stage(steps):
    before, after = steps["pack"]
    enc, want = PieceEncoder(packing.vocabulary_path("word_bpe_49k.json")), collections.Counter()
    for r in before:
        ids = np.array(enc.whole(r["text"] or "") + [1], "<u4")
        for k, s in enumerate(range(0, len(ids), 4096)):
            want[(r["doc_id"], k, s, len(ids[s : s + 4096]), zlib.crc32(ids[s : s + 4096].tobytes()))] += 1
    assert collections.Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in after) == want
    places = collections.defaultdict(list)
    for r in after:
        places[r["sequence_id"]].append((r["offset"], r["length"]))
    for parts in places.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 4096
    assert len(places) <= -(-sum(r["length"] for r in after) // 4096) * 1.05 + 1


def test_run_is_the_stages_in_order(spark, steps):
    """On the table as given: each stage reads what the one before wrote."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF)
    key = lambda df: sorted(map(tuple, df.select("doc_id", "piece", "start", "length", "ids_crc32").collect()))
    assert key(corpus_pipeline.run(spark, SF)) == key(docs)


def test_empty_input(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF)
        assert docs.count() == 0
