import itertools

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from lakejoin.llm import curriculum, merkle, pieces, queries, rollup
from lakejoin.llm.common import stored


@pytest.mark.parametrize("name", list(queries.ORACLES))
def test_oracle(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "labels"):
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    ours, theirs = queries.QUERIES[name](spark, sf).toPandas(), con.execute(queries.ORACLES[name]).df()
    assert sorted(ours.columns) == sorted(theirs.columns)
    text = lambda v: "null" if v is None or v != v else f"{float(v):.9f}" if isinstance(v, (int, float)) else str(v)
    rows = lambda df: sorted(tuple(map(text, r)) for r in df[sorted(df.columns)].astype(object).itertuples(index=False))
    assert rows(ours) == rows(theirs)


def water(sizes, weights, share, most):
    """Reshare the excess over the caps until none is left."""
    total, capped = share * sum(sizes.values()), set()
    while True:
        free = [s for s in sizes if s not in capped]
        rest = total - sum(most * sizes[s] for s in capped)
        out = {s: most * sizes[s] if s in capped else rest * weights[s] / sum(weights[f] for f in free) for s in sizes}
        over = {s for s in free if out[s] > most * sizes[s] + 1e-9}
        if not over:
            return out
        capped |= over


def test_mix(spark, docs, odd, nothing):
    rows = curriculum.plan(docs).collect()
    sizes = {r.source: r.source_size for r in rows}
    weights = dict(zip(sorted(sizes), itertools.cycle((3, 1, 2))))
    expected = water(sizes, weights, 1.5, 2)
    for s in sizes:
        assert {round(r.target, 6) for r in rows if r.source == s} == {round(expected[s], 6)}
        assert abs(sum(r.taken for r in rows if r.source == s) - expected[s]) <= 1
    assert all(r.taken <= 2 * r.size for r in rows)
    again = curriculum.plan(docs.repartition(13)).collect()
    assert {(r.doc_id, r.taken) for r in rows} == {(r.doc_id, r.taken) for r in again}
    assert curriculum.plan(odd).count() == 10 and curriculum.plan(nothing).count() == 0
    out = curriculum.stage(spark, odd, "")
    assert out.columns == odd.columns and curriculum.stage(spark, nothing, "").count() == 0


def test_positions_follow_the_schedule(spark):
    for curve in curriculum.CURVES:
        share = spark.range(1001).select((F.col("id") / 1000).alias("p"))
        t = np.array([r.t for r in share.select(curriculum.demand_time(F.col("p"), curve).alias("t")).collect()])
        fine = np.linspace(0, 1, 20001)
        cum = np.cumsum(np.interp(fine, curriculum.KNOTS, curve))
        assert (np.diff(t) >= 0).all() and np.abs(np.interp(t, fine, cum / cum[-1]) - np.linspace(0, 1, 1001)).max() < 1e-3


def test_mix_sorts_and_repeats(spark, docs):
    got = curriculum.mix(docs).collect()
    assert [r.mix_position for r in got] == sorted(r.mix_position for r in got)
    taken = {r.doc_id: r.taken for r in curriculum.plan(docs).collect()}
    words = {}
    for r in got:
        words[r.doc_id] = words.get(r.doc_id, 0) + len((r.text or "").encode().split())
    assert words == {d: n for d, n in taken.items() if n > 0}


@pytest.fixture(scope="module")
def coder():
    return pieces.Pieces(pieces._model("/opt/tokenizers/" + pieces.MODEL), 4)


def every_path(coder, s):
    edges, _ = coder.lattice(s)

    def go(at):
        if at == 0:
            yield 0.0, ()
        for i, w, ids in edges[at]:
            for score, path in go(i):
                yield score + w, path + ids

    return sorted(go(len(s)), key=lambda x: -x[0])


@pytest.mark.parametrize("text", ["Hello wörld", "a  b\n c", "漢字 test", "don't stop.", " lead", "x\ty", "the the", "\U0001f600!"])
def test_nbest_against_all_paths(coder, text):
    s = pieces.MARK + text.replace(" ", pieces.MARK)
    got = coder.encode_nbest(text)
    assert [round(a, 6) for a, _ in got] == [round(a, 6) for a, _ in every_path(coder, s)[: len(got)]]
    assert len({tuple(i) for _, i in got}) == len(got) and all(coder.decode(i) == text for _, i in got)
    ids, score, second = coder.encode(text)
    assert np.frombuffer(ids, "<i4").tolist() == got[0][1] and score == pytest.approx(got[0][0])
    assert len(got) < 2 or second == pytest.approx(got[1][0])


def test_pieces_round_trip(spark, odd, nothing, docs):
    for df in (odd, nothing, docs):
        back = pieces.decoded(pieces.encoded(df))
        assert sorted((r.doc_id or 0, r.text) for r in back.collect()) == sorted((r.doc_id or 0, r.text or "") for r in df.select("doc_id", "text").collect())


def brute_root(text):
    import hashlib

    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    return sha(",".join(sha(",".join(sha(p) for p in s.split("\n"))) for s in text.split("\n\n")))


def brute_leaves(text):
    import hashlib

    import regex

    return {hashlib.md5(p.encode()).hexdigest()[: merkle.DIGITS] for p in regex.findall(merkle.PATTERN, text)}


def brute_likeness(a, b):
    least = sorted(a | b)[: merkle.SKETCH]
    return sum(x in a and x in b for x in least) / len(least) if least else 1.0


def test_merkle(spark, odd, nothing, docs):
    got = {r.doc_id: r for r in merkle.compared(docs).collect()}
    rows = sorted((r.doc_id, r.text or "") for r in docs.select("doc_id", "text").collect())
    for (d, t), (_, after) in zip(rows, rows[1:] + rows[:1]):
        q = len(t) // 4
        edited = t[: len(t) - q] + after[:q]
        print_of = lambda x: brute_root(x) + "".join(sorted(brute_leaves(x))[: merkle.SKETCH])
        assert got[d].fingerprint == print_of(t) and got[d].edited_fingerprint == print_of(edited) and got[d].n_chars == len(t)
        assert (got[d].fingerprint == got[d].edited_fingerprint) == (t == edited)
        a, b, c = (set(sorted(brute_leaves(x))[: merkle.SKETCH]) for x in (t, edited, after))
        assert got[d].near_edited == pytest.approx(brute_likeness(a, b)) and got[d].near_next == pytest.approx(brute_likeness(a, c))
        if t == edited:
            assert got[d].edit_section is None
        else:
            s, e = t.split("\n\n"), edited.split("\n\n")
            k = next(i for i in range(max(len(s), len(e))) if s[i : i + 1] != e[i : i + 1])
            assert got[d].edit_section == k
    assert sum(r.near_edited > r.near_next for r in got.values()) > 0.9 * len(got)
    assert merkle.compared(nothing).count() == 0
    one = merkle.compared(odd.where("doc_id = 6")).first()
    assert one.near_next == 1.0


def test_merkle_versions_and_rows_without_id(spark, odd):
    """Rows that share an id, null ids too, are each followed by the least text of the next id."""
    rows = [(r.doc_id, r.text or "") for r in odd.collect()] + [(None, "b"), (None, "a"), (8, "zz")]
    got = sorted((r.doc_id if r.doc_id is not None else 99, r.fingerprint[:64], r.edited_sha256) for r in merkle.compared(spark.createDataFrame(rows, "doc_id bigint, text string")).collect())
    import hashlib

    ids = sorted({99 if d is None else d for d, _ in rows})
    least = {i: min(t.encode() for d, t in rows if (99 if d is None else d) == i).decode() for i in ids}
    want = []
    for d, t in rows:
        i = 99 if d is None else d
        after = least[ids[(ids.index(i) + 1) % len(ids)]]
        q = len(t) // 4
        want.append((i, brute_root(t), hashlib.sha256((t[: len(t) - q] + after[:q]).encode()).hexdigest()))
    assert got == sorted(want)


def test_likeness_is_close_to_the_leaves(spark):
    texts = [" ".join(f"word{i} and{i * 7 % 311}." for i in range(n, n + 900)) for n in (0, 90, 300, 600, 5_000)]
    df = spark.createDataFrame([(a, b) for a in texts for b in texts], "a string, b string")
    fp = lambda c: merkle.fingerprint(merkle.tree(F.col(c))["root"], F.col(c))
    for r in df.select("a", "b", merkle.likeness(fp("a"), fp("b")).alias("n")).collect():
        x, y = brute_leaves(r.a), brute_leaves(r.b)
        assert abs(r.n - len(x & y) / len(x | y)) < 4 * 0.5 / merkle.SKETCH**0.5


def test_successors_over_sparse_ids(spark):
    ids = sorted({0, 1, 2, 1023, 1024, 5_000_000, 2**40, 2**40 + 1, -5, -(2**50), 2**63 - 1})
    got = {r.k: r.next for r in merkle.successors(spark.createDataFrame([(i,) for i in ids], "k bigint"), ids[0], ids[-1]).collect()}
    assert got == dict(zip(ids, ids[1:] + ids[:1]))


def test_edits_locate_changes(spark):
    df = spark.createDataFrame([("a\nb\n\nc\nd", "a\nB\n\nc\nd\ne"), ("x", "x")], "l string, r string")
    got = df.select(merkle.edits(merkle.tree(F.col("l")), merkle.tree(F.col("r"))).alias("e")).collect()
    assert [tuple(x) for x in got[0].e] == [(0, 1), (1, 2)] and got[1].e == []


def test_rollup(spark, tmp_path):
    schema = "op string, source string, lang string, version string, tokens bigint, chars bigint, old_tokens bigint, old_chars bigint"
    change = lambda *rows: spark.createDataFrame(list(rows), schema)
    store = rollup.Rollup(spark, f"file://{tmp_path}/r")
    assert store.totals().count() == 0
    first = change(("insert", "a", None, "v1", 10, 50, None, None), ("insert", "a", None, "v1", 5, 20, None, None), ("insert", None, "en", "v1", 7, None, None, None))
    assert store.commit("b1", first) and not store.commit("b1", first)
    assert store.commit("b2", change(("delete", "a", None, "v1", 5, 20, None, None), ("revise", "a", None, "v1", 12, 55, 10, 50), ("delete", None, "en", "v1", 7, 0, None, None)))
    total = lambda: {tuple(r) for r in store.totals().collect()}
    assert total() == {("a", None, "v1", 1, 12, 55)}
    store.compact()
    assert total() == {("a", None, "v1", 1, 12, 55)} and not store.commit("b2", first) and store.commit("b3", first.limit(0))
    store.compact()
    assert store.batches() == ["b1", "b2", "b3"] and total() == {("a", None, "v1", 1, 12, 55)}
    with pytest.raises(Exception, match="unknown operation"):
        store.commit("b4", change(("upsert", "a", "en", "v1", 1, 1, None, None)))
    assert "b4" not in store.batches()


def test_tokenizer_counts(spark, odd):
    import public_tokenizers as P
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    t.encode_special_tokens = True
    got = {r.doc_id: r for r in rollup.tokenizer_counts(odd, {"a": P.path("byte_bpe_50k.tiktoken")}).collect()}
    assert {d: r.tokens for d, r in got.items()} == {r.doc_id: [len(t.encode(r.text or "", add_special_tokens=False).ids)] for r in odd.collect()}
    assert {d: r.chars for d, r in got.items()} == {r.doc_id: len(r.text or "") for r in odd.collect()}


def test_rollup_query_against_counting_all(spark, sf, docs):
    """Totals of the query, whole texts counted by another implementation of the vocabulary where there is one."""
    import base64

    import public_tokenizers as P
    import tiktoken
    from tokenizers import Tokenizer

    one = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    one.encode_special_tokens = True
    with open(P.path("byte_bpe_multi_50k.tiktoken"), "rb") as f:
        two = tiktoken.Encoding("two", pat_str=P.PATTERN, mergeable_ranks={base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}, special_tokens={})
    marks = {r.doc_id: r for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    want: dict = {}
    for r in docs.collect():
        mark = marks.get(r.doc_id)
        if mark is not None and mark.quality == 0:
            continue
        gone = mark is not None and mark.toxic == 1
        text = r.text or ""
        for version, n in (("bpe-50k", len(one.encode(text, add_special_tokens=False).ids)), ("bpe-multi-50k", 0 if gone else len(two.encode_ordinary(text)))):
            total = want.setdefault((r.source, r.lang, version), [0, 0, 0])
            total[0] += 1
            total[1] += n
            total[2] += 0 if gone and version == "bpe-multi-50k" else len(text)
    got = {(r.source, r.lang, r.version): [r.docs, r.tokens, r.chars] for r in queries.QUERIES["op8_token_rollup"](spark, sf).collect()}
    assert got == want


def test_pipeline_stages(spark, sf, docs):
    now, before = docs, docs.count()
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        now = stored(stage(spark, now, sf))
        if k + 1 < len(corpus_pipeline.STAGES):
            assert now.columns == docs.columns and now.dtypes == docs.dtypes
        if k < 3:
            assert 0 < now.count() <= before
            before = now.count()
        if name == "quality_classifier":
            marks = spark.read.parquet(f"{sf}/labels.parquet")
            kept = now.join(marks, "doc_id").groupBy("quality").count().collect()
            good = marks.where("quality = 1").count()
            assert {r.quality: r["count"] for r in kept}[1] >= 0.95 * good
    assert set(now.columns) == {"doc_id", "pieces", "score", "scores", "ids_hashes", "file_no", "row_no"}


def test_queries_give_all_segmentations(spark, coder):
    """What op6 and the stage return is the agenda search's N best, whole texts included."""
    texts = ["The cat sat on the mats.", "hello ▁ world\nagain", "a", "", None]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    for r in pieces.encoded(df, nbest=4).collect():
        want = coder.encode_nbest(texts[r.doc_id])
        assert r.scores == pytest.approx([s for s, _ in want]) and len(set(r.ids_hashes)) == len(want)
        got = coder.best(texts[r.doc_id])
        assert [pieces.ids_hash(ids) for _, ids in got] == r.ids_hashes
        assert all(coder.decode(np.frombuffer(ids, "<i4").tolist()) == (texts[r.doc_id] or "") for _, ids in got)
    assert len(coder.best(texts[0])) == 4
