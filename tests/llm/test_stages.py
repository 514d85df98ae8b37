import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from lakejoin.llm import chaining, common, curriculum, nbsvm, pieces, simhash

CLASHES = "__score string, score string, mix_words string, mix_n string, mix_position string, __spans string, cuts string, nth string, `count` string, root string, `a.b` string"


@pytest.fixture(scope="module")
def clashing(docs):
    names = [x.split()[0].strip("`") for x in CLASHES.split(", ")]
    return docs.select("*", *[F.lit(f"own {n}").alias(n) for n in names]), names


@pytest.mark.parametrize("stage", [nbsvm.stage, simhash.stage, chaining.stage, curriculum.stage])
def test_own_columns_pass_through(spark, sf, clashing, stage):
    df, names = clashing
    got = stage(spark, df, sf)
    assert got.columns == df.columns
    rows = got.collect()
    assert rows and all(r[n] == f"own {n}" for r in rows for n in names)


def test_quality_stage_keeps_what_the_scores_say(spark, sf, docs):
    model = nbsvm.train(docs, common.labels(spark, sf))
    want = {r.doc_id for r in nbsvm.score(docs, model).where("score >= 0.5").collect()}
    assert {r.doc_id for r in nbsvm.stage(spark, docs, sf).collect()} == want


def test_training_order_survives_many_files(spark, docs, tmp_path):
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    spark.conf.set("spark.sql.shuffle.partitions", "8")
    try:
        want = [r.doc_id for r in curriculum.mix(docs).collect()]
        curriculum.stage(spark, docs, "").write.parquet(f"{tmp_path}/mixed")
        assert len(list((tmp_path / "mixed").glob("part-*.parquet"))) > 4
        back = pieces.stage(spark, spark.read.parquet(f"{tmp_path}/mixed"), "")
        assert [r.doc_id for r in back.orderBy("file_no", "row_no").collect()] == want
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", "4")
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")


def test_places_without_files(spark, docs):
    got = pieces.placed(docs.orderBy("doc_id").limit(50)).orderBy("file_no", "row_no").collect()
    assert [r.doc_id for r in got] == sorted(r.doc_id for r in got)


def test_unbroken_runs_take_time_in_proportion():
    coder = pieces.Pieces(pieces._model("/opt/tokenizers/" + pieces.MODEL), 2)
    took = []
    for n in (50_000, 200_000):
        start = time.process_time()
        best = coder.encode_nbest("ab\u6f22c" * (n // 4))
        took.append(time.process_time() - start)
        assert len(best) == 2 and coder.decode(best[1][1]) == "ab\u6f22c" * (n // 4)
    assert took[1] < 10 * took[0]


def test_memory_stays_bounded(monkeypatch):
    monkeypatch.setattr(pieces, "CHUNKS", 20)
    coder = pieces.Pieces(pieces._model("/opt/tokenizers/" + pieces.MODEL), 2)
    for i in range(30):
        text = " ".join(f"w{i}x{k}" for k in range(7)) + " " + "y" * (pieces.LONGEST + 5)
        assert coder.many([text, text])[0] == coder.best(text)
        assert len(coder.chunk) <= 20 and len(coder.old) <= 20 and not any(len(k) > pieces.LONGEST for k in (*coder.chunk, *coder.old))


@pytest.mark.parametrize("n", [1, 2, 5])
def test_searches_in_step_find_what_single_searches_find(docs, n):
    """Every chunk of the table, and odd ones, against the single-string agenda search."""
    coder = pieces.Pieces(pieces._model("/opt/tokenizers/" + pieces.MODEL), n)
    texts = [r.text for r in docs.select("text").collect()] + ["\u6f22\u5b57 \U0001f600x", "a", "aaaaaaaaaaaa", "\u0001\u0002"]
    chunks = sorted({c for t in texts for c in (coder.runs(t) if t else []) if c and len(c) <= 24})
    assert len(chunks) > 2_000
    got = coder._short(chunks)
    for c in chunks[:: max(1, len(chunks) // 4_000)]:
        want = coder.search(c, n)
        assert [s for s, _ in got[c]] == pytest.approx([s for s, _ in want])
        assert len({i for _, i in got[c]}) == len(want)
        gaps = [a - b for (a, _), (b, _) in zip(want, want[1:])]
        if all(g > 1e-9 for g in gaps) and len(want) == n == 1:
            assert [tuple(np.frombuffer(i, "<i4").tolist()) for _, i in got[c]] == [i for _, i in want]
