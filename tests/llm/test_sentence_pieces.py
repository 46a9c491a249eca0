"""Operator 2 against the library's own Viterbi: the model file with its type set to unigram."""

import numpy as np
import pytest

sentencepiece = pytest.importorskip("sentencepiece")
tokenizers = pytest.importorskip("public_tokenizers")

from saferoads.llm.sentence_pieces import Encoder, Pieces, decode, decode_documents, encode_documents, fields  # noqa: E402

TEXTS = ["", "a", " ", "Hello world", "  two  spaces ", "naïve café, 東京 \U0001f600!", "tab\tand\nline", "x" * 60, "ab " * 20, "Eauouon.\nEnpaeux leaux le ouè eauenaux", "▁literal▁marker", "thntblere of then, edtioner"]


@pytest.fixture(scope="module")
def model():
    with open(tokenizers.path("piece_bpe_32k.model"), "rb") as f:
        return f.read()


def as_unigram(raw: bytes) -> bytes:
    """The model with model_type = 1 appended to its trainer settings (the last value of a field counts)."""

    def varint(n):
        out = b""
        while n > 127:
            out += bytes([n & 127 | 128])
            n >>= 7
        return out + bytes([n])

    trainer = next(v for n, v in fields(raw) if n == 2) + bytes([3 << 3, 1])
    return raw + bytes([2 << 3 | 2]) + varint(len(trainer)) + trainer


def test_equals_the_library(model):
    sp = sentencepiece.SentencePieceProcessor(model_proto=as_unigram(model))
    rng = np.random.default_rng(3)
    words = ["the", "tion", "ré", "ß", "zz", "42", "!!", "日本", "eauou", "Thanks"]
    texts = TEXTS + [" ".join("".join(rng.choice(words, rng.integers(1, 5))) for _ in range(rng.integers(1, 8))) for _ in range(60)]
    ids, bounds = Encoder(Pieces(model)).encode([t.encode() for t in texts])
    for i, t in enumerate(texts):
        mine = ids[bounds[i] : bounds[i + 1]].tolist()
        if not t:
            assert mine == []
            continue
        best = sp.nbest_encode(t, nbest_size=2)[0]  # the lattice's best path; encode() takes shortcuts
        if not any(sp.is_byte(x) for x in best):
            mine_score, best_score = (sum(sp.get_score(x) for x in path) for path in (mine, best))
            assert mine_score >= best_score and (mine_score == best_score or best_score < -1e8), t  # single floats lose digits there
        assert sp.decode(mine) == t.replace("▁", " ")


def test_round_trip(spark, model):
    df = spark.createDataFrame([(i, t) for i, t in enumerate(TEXTS)] + [(99, None), (3, "Hello world")], "doc_id bigint, text string")
    coded = encode_documents(df, model)
    assert all(r["round_trip"] for r in coded.collect())
    back = {r["doc_id"]: r["text"] for r in decode_documents(coded, model).collect()}
    assert all(back[i] == t.replace("▁", " ") for i, t in enumerate(TEXTS)) and back[99] == ""
    assert encode_documents(df.limit(0), model).count() == 0


def test_long_word_equals_batched_words(model):
    from saferoads.llm.sentence_pieces import solve_equal, solve_long

    pieces = Pieces(model)
    for t in (" internationalisation", " ééé日本語x", " zzzz!!thethe", " \U0001f600ab"):
        row = np.frombuffer(t.encode(), np.uint8)
        assert solve_long(row, pieces)[0].tolist() == solve_equal(row[None, :], pieces)[0].tolist()


def test_small_cache_gives_the_same(model):
    pieces = Pieces(model)
    a, b = Encoder(pieces), Encoder(pieces, keep=3)
    for t in TEXTS:
        x, y = a.encode([t.encode()] * 2), b.encode([t.encode()] * 2)
        assert x[0].tolist() == y[0].tolist() and decode(*x, pieces) == [t.replace("▁", " ").encode()] * 2
