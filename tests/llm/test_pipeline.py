"""The corpus pipeline, stage by stage, against plain Python on a small fixture."""

import collections

import corpus_pipeline
from tests.llm.test_operators import texts_of
from tilestar.llm import packing, simhash

WORDS = "river stone cloud paper green winter table music window garden silver morning coffee letter".split()


def sentence(seed: int, n: int) -> str:
    return " ".join(f"{WORDS[(seed * 7 + k * k + k * seed) % len(WORDS)]}{(seed * 31 + k * 17) % 997}" for k in range(n))


def test_stages(spark, tmp_path):
    shared = sentence(99, 60)
    rows = [(k, sentence(k, 40) + "\n" + sentence(k + 500, 30), "en", "s", 1) for k in range(12)]
    rows += [(20, "too short", "en", "s", 1), (21, rows[3][1], "en", "s", 1), (22, sentence(22, 30) + " " + shared, "en", "s", 1), (23, sentence(23, 30) + " " + shared + " end", "en", "s", 1)]
    rows += [(24, "x% y% z% " * 20, "en", "s", 1), (25, None, "en", "s", None)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    names = [name for name, _ in corpus_pipeline.STAGES]
    assert names == ["quality_rules", "line_dedup", "simhash_near_dedup", "substring_dedup", "best_fit_packing"]
    ids = []
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, str(tmp_path))
        docs.write.parquet(f"{tmp_path}/{name}")
        docs = spark.read.parquet(f"{tmp_path}/{name}")
        ids.append(sorted({r["doc_id"] for r in docs.select("doc_id").collect()}))
        if name != names[-1]:
            assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
        if name == "substring_dedup":
            last = dict(texts_of(docs))
    clean = [*range(12), 22, 23]
    assert ids[0] == [*range(12), 21, 22, 23]
    assert ids[1] == ids[0]
    assert set(ids[2]) == {*clean, 21}  # the copy's lines are gone, and no other document is empty
    assert last[22] == sentence(22, 30) and last[23] == sentence(23, 30) + " end" and last[21] == ""
    want = collections.Counter({i: len(packing.cuts(1)) for i in ids[3]})
    assert collections.Counter(r["doc_id"] for r in docs.collect()) == want
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == docs.count()
    assert simhash.fingerprint("") == 0
