"""Each operator on awkward small tables, against brute force."""

import collections
import hashlib
import os
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from blockmatch.llm import exact, hyperminhash, langid, lines, media, mixing, packing, quality, substrings, tokenstore
from blockmatch.llm.common import Workspace
from blockmatch.llm.tokens import PieceEncoder

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, digest string, key long, size long, rate double"
rng = random.Random(7)
VOCAB = ["".join(rng.choices("abcdefgh", k=rng.randint(1, 6))) for _ in range(80)]


def words(n):
    return " ".join(rng.choices(VOCAB, k=n))


def rows():
    base = words(60)
    near = base.split()
    near[30] = "changed"
    texts = [None, "", " \n\t ", base, base, base.replace(" ", "  "), " ".join(near), base.upper(), "one two", "One two", "x", words(9000), "café ñandú 日本 😀", "line a\nline b\n\nline a", "<|endoftext|> it's 1st"]
    texts += [f"{words(20)}\nShared line of all sites.\n{words(15)}" for _ in range(14)]
    texts += [words(rng.randint(1, 90)) for _ in range(25)]
    out = [(i, t, "ab"[i % 2] if i % 7 else None, f"s{i % 12}" if i % 11 else None, 1, "clash", 2, 3, 0.5) for i, t in enumerate(texts)]
    return out + [out[4]]  # a repeated row


ROWS = rows()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def find_all(text):
    return WORD.findall(text or "")


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "byte_bpe_50k.json"])
def test_cached_encoding_is_exact(name):
    enc = PieceEncoder(packing.vocabulary_path(name), most=50)
    signs = ["a", "B", "é", " ", "  ", "\n", "\t", "'s", "'", "1", ".", ",", "!!", "Σ", "İ", "é", "<|endoftext|>", "日本", "\r\n", "Word", "\x1c", "😀", " ", "ß"]
    texts = ["".join(rng.choices(signs, k=rng.randint(0, 12))) for _ in range(3000)] + [r[1] or "" for r in ROWS]
    for i in range(0, len(texts), 100):
        part = texts[i : i + 100]
        assert [e.tolist() for e in enc.encode(part)] == [enc.whole(t) for t in part]


def test_packing(docs, empty):
    path = packing.vocabulary_path("word_bpe_49k.json")
    got = packing.pack_documents(docs, path, capacity=256).toPandas()
    enc = PieceEncoder(path)
    want = collections.Counter()
    for r in ROWS:
        ids = np.array(enc.whole(r[1] or "") + [1], "<u4")
        for k, s in enumerate(range(0, len(ids), 256)):
            want[(r[0], k, s, len(ids[s : s + 256]), zlib.crc32(ids[s : s + 256].tobytes()))] += 1
    assert collections.Counter(map(tuple, got[["doc_id", "piece", "start", "length", "ids_crc32"]].itertuples(index=False))) == want
    got = got.sort_values(["sequence_id", "offset"])
    ends = got.groupby("sequence_id").length.cumsum()
    assert (got.offset == ends - got.length).all() and ends.max() <= 256
    assert got.sequence_id.nunique() <= -(-got.length.sum() // 256) * 1.1 + 1
    seqs = packing.packed_sequences(docs, path, capacity=256).toPandas()
    assert seqs.length.sum() == got.length.sum() and (seqs.ids.map(len) == 4 * seqs.length).all()
    assert packing.pack_documents(empty, path).count() == 0


@pytest.mark.parametrize("seed", range(5))
def test_packing_plan(seed):
    r = random.Random(seed)
    hist = {length: r.randint(1, 40) for length in r.sample(range(1, 101), 60)}
    plan = packing.best_plan(hist, 100)
    bins, ranks = collections.defaultdict(list), collections.defaultdict(list)
    for length, low, count, first, offset in plan:
        ranks[length] += range(low, low + count)
        for s in range(first, first + count):
            bins[s].append((offset, length))
    assert {k: sorted(v) for k, v in ranks.items()} == {k: list(range(v)) for k, v in hist.items()}
    for parts in bins.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 100
    assert len(bins) <= -(-sum(k * v for k, v in hist.items()) // 100) * 1.08 + 2


def test_mixing(docs, empty):
    got = mixing.mix_table(docs).toPandas()
    size = collections.Counter()
    for r in ROWS:
        size[r[3]] += len(find_all(r[1]))
    for _, r in got.iterrows():
        assert r["taken"] in (0, r["size"], 2 * r["size"]) and r["target"] <= 2 * r["source_size"] + 1e-6
    per = got.groupby("target").first()
    assert abs(sum(min(2.0 * s, t) for t, s in per.source_size.items()) - 1.5 * sum(size.values())) < 1e-3 * sum(size.values()) or len(per) < len(size)
    again = mixing.mix_table(docs.repartition(2)).toPandas()
    assert sorted(map(tuple, got.itertuples(index=False))) == sorted(map(tuple, again.itertuples(index=False)))
    mixed = mixing.mix_documents(docs)
    assert mixed.columns == docs.columns
    assert sum(len(find_all(r["text"])) for r in mixed.collect()) == got.taken.sum()
    assert mixing.mix_table(empty).count() == 0


def test_lines(docs, empty):
    sites, first = collections.defaultdict(set), {}
    for r in ROWS:
        for x in (r[1] or "").split("\n"):
            if bare := x.strip(lines.BLANKS):
                sites[bare].add(r[3])
                first[bare] = min(first.get(bare, r[0]), r[0])
    common = {b for b, s in sites.items() if len(s) >= 10}
    assert common
    want = sorted((r[0], None if r[1] is None else "\n".join(x for x in r[1].split("\n") if not (x.strip(lines.BLANKS) in common and first[x.strip(lines.BLANKS)] != r[0]))) for r in ROWS)
    got = lines.dedup_lines(docs)
    assert got.columns == docs.columns
    assert sorted(((r["doc_id"], r["text"]) for r in got.collect()), key=str) == sorted(want, key=str)
    assert lines.dedup_lines(empty).count() == 0


def test_line_sketch_counts_far_from_the_threshold(spark):
    n = [1, 3, 9, 40, 300]
    df = spark.createDataFrame([(k, f"site{i}") for k in n for i in range(k)], "k int, site string")
    cols = lines.lanes(F.col("site"))
    merged = df.select("k", *[c.alias(f"s{i}") for i, c in enumerate(cols)]).groupBy("k").agg(*[F.bit_or(f"s{i}").alias(f"s{i}") for i in range(len(cols))])
    for r in merged.select("k", lines.estimated([F.col(f"s{i}") for i in range(len(cols))]).alias("e")).collect():
        assert 0.5 * r["k"] <= r["e"] <= 1.6 * r["k"]


def test_language(spark, docs, empty):
    data = [(i, words(30) if i % 2 else " ".join(rng.choices(["ñandu", "llave", "queso", "zorro"], k=30)), "ab" if i % 2 else "es") for i in range(80)] + [(90, None, "ab"), (91, "12 34", "ab"), (92, "", None)]
    df = spark.createDataFrame(data, "doc_id long, text string, lang string").withColumn("held_out", F.col("doc_id") % 5 == 0)
    got = langid.predict_languages(df, langid.fit_languages(df, ~F.col("held_out"))).toPandas().set_index("doc_id")
    for i, _, lang in data[:80]:
        assert got.lang_pred[i] == lang and 0 <= got.score[i] <= 1
    assert list(got.lang_pred[[90, 91, 92]]) == ["und"] * 3
    none = empty.withColumn("held_out", F.lit(False))
    assert langid.predict_languages(none, langid.fit_languages(none, ~F.col("held_out"))).count() == 0


def test_sliced_filters_have_no_false_negatives():
    m = langid.SlicedFilters.fit([("a", "hello world " * 5), ("b", "bonjour monde " * 5)])
    count, n = m.counts(["hello world " * 5])
    assert count[0, 0] >= n[0] * 0.9 and count[0, 1] < n[0] * 0.5


def test_token_store(spark, docs, empty):
    path = packing.vocabulary_path("byte_bpe_50k.json")
    ws = Workspace(spark, "t")
    store = tokenstore.TokenStore(ws).write(docs, path)
    enc = PieceEncoder(path)
    streams = sorted((r[0], enc.whole(r[1] or "") + [0]) for r in ROWS)
    want, at = [], 0
    for i, ids in streams:
        want.append((i, at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()), True))
        at += len(ids)
    assert sorted(map(tuple, store.check().collect())) == want
    assert store.broken().count() == 0 and len(store.root()) == 64
    back = {r["doc_id"]: np.frombuffer(r["ids"], "<u2").tolist() for r in store.ids(docs.filter("doc_id in (3, 5, 11)")).collect()}
    assert back == {i: x for i, x in streams if i in (3, 5, 11)}
    held = store.read("documents").dropDuplicates(["doc_id"]).select(F.explode(F.arrays_zip("digests", "ids")).alias("c"))
    own = held.filter("c.ids is not null").select("c.digests")
    assert own.count() == own.distinct().count() == held.select("c.digests").distinct().count() < held.count()
    none = tokenstore.TokenStore(Workspace(spark, "t")).write(empty, path)
    assert none.check().count() == none.broken().count() == 0 and none.root() is None
    # a store in which one chunk's bytes were changed, and one whose documents were exchanged
    spoilt = tokenstore.TokenStore(Workspace(spark, "t"))
    store.read("index").write.parquet(spoilt.ws.path("index"))
    odd = F.when(F.col("doc_id") == 11, F.transform("ids", lambda x: F.concat(x, F.lit(b"\0\0")))).otherwise(F.col("ids"))
    store.read("documents").withColumn("ids", odd).write.parquet(spoilt.ws.path("documents"))
    assert [r["doc_id"] for r in spoilt.check().filter("not whole").collect()] == [11]
    swapped = F.when(F.col("doc_id") == 11, F.lit(b"x" * 16)).otherwise(F.col("root"))
    store.read("index").withColumn("root", swapped).write.mode("overwrite").parquet(spoilt.ws.path("index"))
    store.read("manifest").write.parquet(spoilt.ws.path("manifest"))
    assert spoilt.broken().count() >= 1


def test_crc_of_joined_parts():
    a, b = b"some bytes", bytes(range(200)) * 9
    joined = tokenstore.shift_crc(np.array([zlib.crc32(a)]), np.array([len(b)]))[0] ^ zlib.crc32(b)
    assert joined == zlib.crc32(a + b)


def brute_windows(data, size=13):
    texts = [(i, find_all(t)) for i, t in data]
    least = {}
    for i, w in sorted(texts, key=lambda x: x[0]):
        for k in range(len(w) - size + 1):
            least.setdefault(tuple(w[k : k + size]), i)
    out = []
    for i, w in texts:
        gone = [False] * len(w)
        for k in range(len(w) - size + 1):
            if least[tuple(w[k : k + size])] < i:
                gone[k : k + size] = [True] * size
        out.append((i, len(w), sum(gone), hashlib.sha256(" ".join(x for x, g in zip(w, gone) if not g).encode()).hexdigest()))
    return sorted(out)


def test_substrings(spark, docs, empty):
    got = substrings.dedup_substrings(docs, chunk_bytes=2000, bucket_words=500)
    assert sorted(map(tuple, got.collect())) == brute_windows([(r[0], r[1]) for r in ROWS])
    data = [(i, " ".join(rng.choices("ab", k=rng.randint(0, 40)))) for i in range(60)] + [(100, " ".join(["x"] * 100)), (101, " ".join(["x"] * 50))]
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(3)
    kept = substrings.dedup_substrings(df, chunk_bytes=300, bucket_words=50, keep_text=True).collect()
    assert sorted(tuple(r)[:4] for r in kept) == brute_windows(data)
    assert all(hashlib.sha256(r["kept_text"].encode()).hexdigest() == r["kept_sha256"] for r in kept)
    assert substrings.dedup_substrings(empty).count() == 0


@pytest.mark.parametrize("weak", [False, True])
def test_exact(docs, empty, weak):
    """A weak digest makes different texts meet; byte verification parts them."""
    digest = (lambda plain: F.unhex(F.lpad(F.hex(F.length(plain) % 3), 2, "0"))) if weak else None
    got = exact.exact_duplicates(docs, digest).collect()
    groups = collections.defaultdict(list)
    for r in ROWS:
        groups["".join(find_all(r[1]))].append((-len(r[1] or ""), r[0]))
    of = {r[0]: "".join(find_all(r[1])) for r in ROWS}
    assert len(got) == len(ROWS)
    for r in got:
        g = groups[of[r["doc_id"]]]
        assert (r["keep_id"], r["group_size"]) == (min(g)[1], len(g))
        assert r["text_sha256"] == hashlib.sha256(of[r["doc_id"]].encode()).hexdigest()
    assert sum(r["kept"] for r in got) == len(groups)
    assert exact.exact_duplicates(empty).count() == 0


def test_digest_index_with_later_batches(spark, docs):
    """Three batches, then a fourth that fills the level; each look-up reads runs through their filters."""
    index = exact.DigestIndex(spark, fanout=4)
    rows = index.ws.save(index.keyed(docs).withColumn("row", F.monotonically_increasing_id()), "rows")
    parts = [rows.filter(F.pmod("doc_id", F.lit(4)) == k) for k in range(4)]
    groups = collections.defaultdict(list)
    for k in range(3):
        index.flush(parts[k])
    assert [len(x) for x in index.levels] == [3]
    for r in ROWS:
        if r[0] % 4 < 3:
            groups["".join(find_all(r[1]))].append((-len(r[1] or ""), r[0]))
    want = {hashlib.sha256(t.encode()).digest(): (min(g)[1], len(g)) for t, g in groups.items()}
    asked = rows.select("digest").distinct()
    found = {bytes(r["digest"]): (r["best"]["keep_id"], r["n"]) for r in index.look_up(asked).collect()}
    assert found == want
    # a filter never misses its own, and seldom lets others through
    for run, part in zip(index.levels[0], parts):
        assert index.may_hold(part.select("digest"), run, "may").filter("not may").count() == 0
        other = spark.range(2000).select(F.unhex(F.sha2(F.col("id").cast("string").cast("binary"), 256)).alias("digest"))
        assert index.may_hold(other, run, "may").filter("may").count() < 100
    index.flush(parts[3])
    index.compact()
    assert [len(x) for x in index.levels] == [0, 1] and not os.path.exists(index.ws.path("run1").removeprefix("file://"))
    whole = {bytes(r["digest"]): r["n"] for r in index.look_up(asked).collect()}
    assert sum(whole.values()) == len(ROWS)
    index.flush(parts[0])
    index.compact(everything=True)
    assert len(index.runs()) == 1 and index.look_up(asked).agg(F.sum("n")).first()[0] == len(ROWS) + parts[0].count()


def brute_components(data):
    low = str.maketrans({chr(i): chr(i + 32) for i in range(65, 91)})
    sets = {}
    for i, t in data:
        w = find_all((t or "").translate(low))
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    parent = {i: i for i in sets}

    def top(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in sets:
        for j in sets:
            if i < j and sets[i] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                a, b = top(i), top(j)
                parent[max(a, b)] = min(a, b)
    return {i: (len(s), top(i)) for i, s in sets.items()}


def test_near_duplicates(spark, docs, empty):
    data = [(r[0], r[1]) for r in ROWS]
    want = brute_components(data)
    got = hyperminhash.near_duplicates(docs).collect()
    assert len(got) == len(ROWS)
    for r in got:
        assert (r["n_shingles"], r["component_id"]) == want[r["doc_id"]] and r["kept"] == (r["component_id"] == r["doc_id"])
    assert hyperminhash.near_duplicates(empty).count() == 0
    kept = hyperminhash.drop_near_duplicates(docs)
    assert kept.columns == docs.columns and {r["doc_id"] for r in kept.collect()} == {c for _, c in want.values()}


def test_near_duplicate_chains(spark):
    """Copies that drift: neighbours are linked, ends aren't; groups of many sizes and very short texts."""
    data, n = [], 0
    for _ in range(6):
        w = words(70).split()
        for _ in range(12):
            data.append((n, " ".join(w)))
            w[rng.randrange(70)] = f"new{n}"
            n += 1
    for k in range(1, 9):
        for _ in range(6):
            data.append((n, " ".join(rng.choices("ab", k=k))))
            n += 1
    got = hyperminhash.near_duplicates(spark.createDataFrame(data, "doc_id long, text string").repartition(4)).collect()
    want = brute_components(data)
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == want


def test_register_estimate():
    for share in (0.3, 0.75, 0.95):
        a = np.unique(np.random.default_rng(1).integers(0, 2**63, 3000).astype(np.uint64) * np.uint64(2))
        n = int(len(a) * 2 * share / (1 + share))
        b = np.unique(np.concatenate((a[:n], np.random.default_rng(2).integers(0, 2**63, len(a) - n).astype(np.uint64) * np.uint64(2))))
        a = np.random.default_rng(3).permutation(a)
        regs = hyperminhash.registers_of([np.sort(a), b])
        true = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
        assert abs(hyperminhash.estimate(regs[:1], regs[1:], np.array([len(a)]), np.array([len(b)]))[0] - true) < 0.2


def test_media(docs, empty):
    got = {r["doc_id"]: r for r in media.media_table(docs).collect()}
    for r in ROWS:
        data = (r[1] or "").encode()
        payload = data + b"\xff" * (-len(data) % 576 if data else 576)
        g = got[r[0]]
        assert (g["n_bytes"], g["payload_bytes"], g["payload_sha256"], g["tail_crc32"]) == (len(data), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]))
    assert got[0]["media_sha256"] == got[1]["media_sha256"] and got[3]["feature"] == got[4]["feature"]
    assert media.media_table(docs).count() == len(ROWS)
    assert media.media_table(empty).count() == 0


def test_shards_are_tar_files(tmp_path):
    import tarfile

    w = media.ShardWriter(f"file://{tmp_path}", "p", most=3000)
    places = [w.add(f"{i}.png", media.to_png(media.payload_of(bytes([i]) * 700))) for i in range(9)]
    w.close()
    assert len({p[0] for p in places}) > 1
    for i, (shard, offset, length) in enumerate(places):
        with tarfile.open(tmp_path / shard) as tar:
            member = tar.getmember(f"{i}.png")
            assert (member.offset_data, member.size) == (offset, length)
            stored = tar.extractfile(member).read()
        assert media.png_header(stored[:33])[:2] == (576, 2)
        assert media.from_png(stored) == media.payload_of(bytes([i]) * 700)


def test_quality(spark, empty):
    data = []
    for i in range(240):
        w = rng.choices(VOCAB, k=40)
        data.append((i, " ".join(w) if i % 3 else " ".join(f"{x.upper()}!!" for x in w)))
    df = spark.createDataFrame([*data, (500, None), (501, "")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 3 > 0), 0) for i in range(0, 240, 2)] + [(777, 1, 0), (4, None, 0)], "doc_id long, quality int, toxic int")
    model = quality.fit_from(df, labels, F.lit(True))
    got = {r["doc_id"]: r["score"] for r in quality.score_documents(df, model).collect()}
    assert all((got[i] >= 0.7) == (i % 3 > 0) for i in range(240)) and 0 <= got[500] <= 1 and got[500] == got[501]
    kept = quality.keep_quality(df.withColumn("score", F.lit("clash")), model)
    assert {r["doc_id"] for r in kept.collect()} - {500, 501} == {i for i in range(240) if i % 3}
    lone = quality.fit_from(empty, labels, F.lit(True))
    assert quality.score_documents(empty, lone).count() == 0


def test_rows_of_the_store_name_the_chunks_they_borrow(spark):
    passage = " ".join(f"word{i} other{i * 7}" for i in range(3000))
    docs = spark.createDataFrame([(1, passage), (2, "a start " + passage), (3, "alone"), (4, None)], "doc_id long, text string")
    store = tokenstore.TokenStore(Workspace(spark, "borrow")).write(docs, tokenstore.vocabulary_path("byte_bpe_50k.json"))
    rows = {r["doc_id"]: r for r in store.read("documents").collect()}
    assert rows[2]["away"] and all(r["away"] is None for k, r in rows.items() if k != 2)
    assert sorted(rows[2]["away"]) == [i for i, x in enumerate(rows[2]["ids"]) if x is None]
    assert all(r["whole"] for r in store.check().collect())
