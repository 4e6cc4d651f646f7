"""Small cases in which a shortened job gives other results than the whole one."""

import random

import pytest
from pyspark.sql import functions as F

from blockmatch.llm import hyperminhash, langid, packing, quality
from blockmatch.llm.tokens import PieceEncoder


def test_near_duplicates_behind_hubs_without_links(spark):
    """Every bucket that the linked pair shares starts with documents that can link with nothing."""
    r = random.Random(3)
    base = [f"w{r.randrange(10**6)}" for _ in range(40)]
    data = [(i, " ".join(base + [f"t{i}x{k}" for k in range(14)])) for i in range(60)]
    data += [(100, " ".join(base)), (101, " ".join([*base[:-1], "changed"]))]
    got = hyperminhash.near_duplicates(spark.createDataFrame(data, "doc_id long, text string").repartition(3)).collect()
    assert {x["doc_id"]: x["component_id"] for x in got} == {i: min(i, 100) for i, _ in data}


def test_quality_learns_from_what_stands_far_behind(spark):
    """Good and bad texts differ after 12,000 characters only."""
    r = random.Random(4)
    clean = lambda n: " ".join(r.choices(["alpha", "beta", "gamma", "delta", "omega"], k=n))
    data = [(i, clean(2600) + " " + (clean(2600) if i % 2 else " ".join(["JUNK!!"] * 2600))) for i in range(60)]
    assert all(len(t[: t.find("JUNK")]) > 12_000 for i, t in data if not i % 2)
    docs = spark.createDataFrame(data, "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(40)], "doc_id long, quality int")
    model = quality.fit_from(docs, labels, F.lit(True))
    got = {x["doc_id"]: x["score"] for x in quality.score_documents(docs, model).collect()}
    assert all((got[i] >= 0.7) == bool(i % 2) for i in range(40, 60)), got


def test_a_rare_language_is_learned(spark):
    """Two documents among 6,000, told apart from the others behind 12,000 characters only."""
    rare = "alpha " * 2100 + "zorro queso llave " * 3000
    docs = spark.range(6000).selectExpr("id as doc_id", "'alpha beta gamma' as text", "'ab' as lang")
    docs = docs.unionByName(spark.createDataFrame([(7001, rare, "es"), (7002, rare, "es")], "doc_id long, text string, lang string"))
    sample = langid.sample_rows(docs, F.lit(True)).groupBy("lang").count().collect()
    assert {r["lang"]: r["count"] for r in sample} == {"ab": langid.SAMPLE_DOCS, "es": 2}
    model = langid.fit_languages(docs, F.lit(True))
    new = spark.createDataFrame([(1, "queso zorro llave", False)], "doc_id long, text string, held_out boolean")
    assert langid.predict_languages(new, model).first()["lang_pred"] == "es"


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "byte_bpe_50k.json"])
def test_texts_with_added_tokens_as_the_library_encodes_them(name):
    from tokenizers import Tokenizer

    path = packing.vocabulary_path(name)
    plain = Tokenizer.from_file(path)
    texts = ["ab <|endoftext|> cd", "x<|endoftext|>y.", "<|startoftext|>\nend", "<|endoftext|>", "no sign", "a <|ENDOFTEXT|> b", ""]
    assert [e.tolist() for e in PieceEncoder(path).encode(texts)] == [plain.encode(t, add_special_tokens=False).ids for t in texts]
