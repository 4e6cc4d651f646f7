"""What a worker remembers between texts is bounded, can be dropped, and changes no score."""

import numpy as np
import pytest

from blockmatch.llm import common, packing, quality, tokens


def test_words_are_forgotten_and_scores_stay():
    texts = ["good words here", "bad words there there", "", "good good"] * 5
    model = quality.fit_quality([(t, i % 2) for i, t in enumerate(texts)])
    first = model.score(texts)
    assert model._words
    model.forget()
    assert not model._words and not model._pairs
    assert np.array_equal(first, model.score(texts))
    assert quality.REMEMBER <= 50_000


def test_workers_are_left_small():
    pa = pytest.importorskip("pyarrow")
    path = packing.vocabulary_path("word_bpe_49k.json")
    stage = lambda batches: (b for b in batches if tokens.encoder(path, packing.PIECES))
    rows = [pa.RecordBatch.from_pydict({"x": [1]})]
    assert list(common.tidy(stage, keep=True)(iter(rows))) == rows and path in tokens._ENCODERS
    assert tokens.encoder(path).most == packing.PIECES
    assert list(common.tidy(lambda batches: batches)(iter(rows))) == rows and not tokens._ENCODERS


def test_lines_share_their_pieces():
    """Arrow texts are encoded in place; line breaks cut, so words on both sides of one aren't remembered as pairs."""
    pa = pytest.importorskip("pyarrow")
    enc = tokens.PieceEncoder(packing.vocabulary_path("byte_bpe_50k.json"))
    texts = [f"so {'abcdefghij'[k // 10]}end.\nÑ{'qrstuvwxyz'[k % 10]}ew one" for k in range(100)]
    odd = ["a \nb", "a\n b", "a\n\nb", "\na", "a\n", "\n", "", " ", "a\r\nb", "a\n\tb", "x <|endoftext|>\ny", "don't\n'll. no", "ǅ\nŉ İ é"]
    want = [enc.whole(t) for t in texts + odd]
    array = pa.array(["left out", *texts, *odd]).slice(1)
    assert [e.tolist() for e in enc.encode(array)] == want
    assert [e.tolist() for e in enc.encode(texts + odd)] == want
    assert len(enc.starts) < 90
