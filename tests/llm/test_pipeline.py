"""The stages of the pipeline against plain versions, on a small folder of tables."""

import random

import pytest
from test_jaccard_join import brute as near_brute
from test_suffix_dedup import brute_words as word_brute

pytest.importorskip("public_tokenizers")

import corpus_pipeline  # noqa: E402
from saferoads.llm import surrogates, toxicity  # noqa: E402
from saferoads.llm.queries import SURROGATE_KEY  # noqa: E402

COLUMNS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    rng = random.Random(4)
    syllables = "th er on an re he in ed nd ha at en es or nt ea ti to it st".split()
    prose = lambda n: " ".join("".join(rng.choice(syllables) for _ in range(rng.randint(2, 4))) for _ in range(n))
    passage = prose(110)
    rows, labels = [], []
    for i in range(160):
        text = prose(rng.randint(20, 160))
        if i % 4 == 0:
            words = text.split()
            words.insert(5, rng.choice(["blockhead", "nitwitted", "scumbaggy"]))
            text = " ".join(words)
        if i % 10 == 1:
            text += " " + passage + " " + prose(30)
        if i % 10 == 2:
            text += f" mail a{i}@host.example.com and 10.0.0.{i}"
        labels.append((i, int(i % 4 == 0)))
        rows.append((i, text))
    rows += [(200, rows[3][1]), (201, rows[5][1] + " tail"), (202, None), (203, ""), (204, passage)]
    path = str(tmp_path_factory.mktemp("tables"))
    spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], COLUMNS).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id bigint, toxic int").write.parquet(f"{path}/labels.parquet")
    return path


def test_stages(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    trained = toxicity.train(docs, spark.read.parquet(f"{folder}/labels.parquet"))
    fine = {r["doc_id"] for r in toxicity.score(docs, trained).where("predicted = 0").collect()}
    kept = []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, folder)
        assert out.columns == docs.columns, name
        before, after = ([(r["doc_id"], r["text"]) for r in df.orderBy("doc_id").collect()] for df in (docs, out))
        if name == "toxicity":
            assert {d for d, _ in after} == fine and {202, 203} <= fine
        elif name == "jaccard_join":
            assert [d for d, _ in after] == sorted({c for _, _, c in near_brute(before, 5, 80)})
        elif name == "suffix_dedup":
            want = {d: t for d, _, t in word_brute(before, 50)}
            assert {d: t or "" for d, t in after} == want and any(want[d] != (t or "") for d, t in before)
        else:
            for (d, t), (_, u) in zip(before, after):
                assert u == (None if t is None else surrogates.replaced(t, SURROGATE_KEY.encode(), {})[0])
                kept.append((d, u))
        docs = spark.createDataFrame(out.collect(), out.schema)
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, folder)
    assert {r["doc_id"] for r in packed.select("doc_id").distinct().collect()} == {d for d, _ in kept}
    whole = corpus_pipeline.run(spark, folder)
    key = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]
    sizes = lambda df: {(r[0], r[4]) for r in df.select(key).collect()}
    assert sizes(whole) == sizes(packed)
