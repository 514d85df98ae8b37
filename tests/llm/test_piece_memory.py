"""What the encoder holds at once, and how often it encodes rows that a mix repeats."""

from collections import Counter

from pyspark.sql import functions as F

from lakejoin.llm import lattices, pieces


def _coder():
    return pieces.Pieces(pieces._model("/opt/tokenizers/" + pieces.MODEL), 2)


def test_searches_in_step_are_bounded_in_characters(docs, monkeypatch):
    texts, sizes, whole = [r.text for r in docs.select("text").collect()], [], lattices.nbest
    want = _coder().many(texts)
    monkeypatch.setattr(lattices, "nbest", lambda trie, weights, unknown, chunks, n: sizes.append(sum(map(len, chunks))) or whole(trie, weights, unknown, chunks, n))
    monkeypatch.setattr(pieces, "STEPPED", 5_000)
    monkeypatch.setattr(pieces, "CUT", 20_000)
    assert _coder().many(texts) == want
    assert len(sizes) > 5 and max(sizes) <= 5_000 + pieces.LONGEST


def test_equal_texts_are_encoded_once(monkeypatch):
    coder, seen = _coder(), []
    monkeypatch.setattr(coder, "runs", lambda t, runs=coder.runs: seen.append(t) or runs(t))
    texts = ["a cat sat", None, "a dog ran", "a cat sat", "", "a cat sat"]
    got = coder.many(texts)
    assert Counter(seen) == {"a cat sat": 1, "a dog ran": 1}
    assert got == [coder.best(t) for t in texts]


def test_stage_brings_repeats_together(spark, odd, docs):
    plain = docs.select("doc_id", "text").union(odd.select("doc_id", "text"))
    twice = plain.repartition(4).union(plain.repartition(3))
    got = pieces.stage(spark, twice, "").withColumn("part", F.spark_partition_id()).collect()
    want = Counter((r.doc_id, r.ids_hashes[0]) for r in pieces.encoded(plain).collect())
    assert Counter((r.doc_id, r.ids_hashes[0]) for r in got) == Counter({k: 2 * n for k, n in want.items()})
    assert len({(r.file_no, r.row_no) for r in got}) == len(got)
    parts: dict = {}
    for r in got:
        parts.setdefault((r.doc_id, r.ids_hashes[0]), set()).add(r.part)
    assert all(len(x) == 1 for x in parts.values())
