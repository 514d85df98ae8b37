import duckdb

from lakejoin.llm import curriculum


def test_query_comes_from_the_pieces_in_training_order(spark, sf, monkeypatch):
    seen, old = [], curriculum.pieces

    def pieces(planned):
        seen.append(old(planned))
        return seen[-1]

    monkeypatch.setattr(curriculum, "pieces", pieces)
    got = curriculum.op5_curriculum_mix(spark, sf).collect()
    read = [r.position for r in got if r.position is not None]
    assert read == sorted(read) and all(r.taken == 0 and r.position is None for r in got[len(read) :])
    assert len(seen) == 1 and sum(r.taken for r in got) == sum(r.words for r in seen[0].collect())
    duckdb.execute(f"create or replace view documents as select * from '{sf}/documents.parquet'")
    assert sorted(map(repr, map(tuple, got))) == sorted(map(repr, duckdb.execute(curriculum.ORACLE).fetchall()))
