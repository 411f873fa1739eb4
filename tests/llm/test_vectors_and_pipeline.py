import numpy as np
import pytest

import corpus_pipeline
from motifscan.llm import ann, langid, lines, neardup
from motifscan.llm.common import Stage, shared_dir, table
from tests.llm.conftest import WORD
from tests.llm.test_documents import brute_groups, brute_lines


def test_neighbours(spark):
    e = table(spark, "/root/testdata/sf0.01", "embeddings")
    rows = e.collect()
    ids = np.array([r.vec_id for r in rows])
    x = np.array([r.embedding for r in rows], float)
    x /= np.sqrt((x * x).sum(1, keepdims=True))
    at = {v: i for i, v in enumerate(ids)}
    got: dict[int, list] = {}
    for r in ann.search(e).collect():
        got.setdefault(r.query_id, []).append(r)
    hit = 0
    for q in ids[ids % 50 == 0]:
        c = x @ x[at[q]]
        c[at[q]] = -2
        best = set(ids[np.lexsort((ids, -c))[:5]])
        mine = sorted(got[q], key=lambda r: r.rank)
        assert [r.rank for r in mine] == [1, 2, 3, 4, 5] and all(abs(c[at[r.vec_id]] - r.score) < 1e-12 for r in mine)
        hit += len(best & {r.vec_id for r in mine})
    assert hit / len(got) / 5 >= 0.9


def test_odd_vectors(spark):
    rows = [(0, [1.0, 0.0]), (50, [1.0, 0.0]), (1, [1.0, 0.0]), (2, None), (3, [0.0, 0.0]), (4, [float("nan"), 1.0]), (5, [0.0, 1.0]), (6, []), (7, [1.0, None]), (None, [1.0, 1.0]), (100, [2.0, 0.0, 1.0])] + [(i, [1.0, 0.0]) for i in range(101, 140)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = sorted((r.query_id, r.rank, r.vec_id) for r in ann.search(df).collect())
    assert got == [(0, i + 1, v) for i, v in enumerate((1, 50, 101, 102, 103))] + [(50, i + 1, v) for i, v in enumerate((0, 1, 101, 102, 103))]
    assert ann.search(df.limit(0)).count() == 0


def test_large_and_small_components(spark):
    """Squares that overflow or vanish don't change cosines."""
    rows = [(0, [1e200, 1e200]), (1, [2.0, 2.0]), (2, [1e-300, -1e-300]), (3, [0.0, 1e-310]), (50, [5e-324, 0.0])]
    got = {(r.query_id, r.vec_id): r.score for r in ann.search(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()}
    want = {(0, 1): 1.0, (0, 2): 0.0, (0, 3): 0.5**0.5, (0, 50): 0.5**0.5, (50, 0): 0.5**0.5, (50, 1): 0.5**0.5, (50, 2): 0.5**0.5, (50, 3): 0.0}
    assert set(got) == set(want) and all(abs(got[k] - x) < 1e-12 for k, x in want.items())


def test_few_candidates_are_all_found(spark, monkeypatch):
    def ranks(rows, **more):
        got = ann.search(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), **more).collect()
        return sorted((r.query_id, r.rank, r.vec_id) for r in got)

    assert ranks([(0, [1.0, 0.0]), (1, [-1.0, 0.0])]) == [(0, 1, 1)]
    x = np.random.default_rng(4).normal(size=(7, 64))
    x[6] = -x[0]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(7, [1.0, 2.0])]
    u = x / np.sqrt((x * x).sum(1, keepdims=True))
    best = [(q, n + 1, int(v)) for q in range(7) for n, v in enumerate([v for v in np.argsort(-(u @ u[q]), kind="stable") if v != q][:5])]
    assert ranks(rows, every=1) == best
    monkeypatch.setattr(ann, "BLOCK", 2)
    assert ranks(rows, every=1) == best
    # an id of many vectors, and rows that repeat
    assert [r[2] for r in ranks([(0, v.tolist()) for v in np.eye(64)[:14] + 1] + [(1, (-np.ones(64)).tolist())])] == [1]
    assert ranks([(0, [1.0, 1.0])] * 20 + [(50, [1.0, 1.0])]) == [(0, 1, 50), (50, 1, 0)]


def test_wide_vectors(spark):
    x = np.random.default_rng(5).normal(size=(1000, 300))
    x /= np.sqrt((x * x).sum(1, keepdims=True))
    got = ann.search(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")).collect()
    best = {(q, int(v)) for q in range(0, 1000, 50) for v in np.argsort(-(x @ x[q]))[1:6]}
    assert len(got) == 100 and len(best & {(r.query_id, r.vec_id) for r in got}) >= 90


def test_settings_follow_the_vectors():
    """Vectors in groups are found by few meetings, those without structure by about half of all."""
    rng = np.random.default_rng(6)
    unit = lambda x: x / np.sqrt((x * x).sum(-1, keepdims=True))
    centres = rng.normal(size=(200, 64))
    groups = unit(centres[rng.integers(0, 200, 3000)] + 0.25 * rng.normal(size=(3000, 64)))
    loose = unit(rng.normal(size=(3000, 64)))
    share = {}
    for name, x in (("groups", groups), ("loose", loose)):
        near = np.argsort(-(x[:64] @ x.T), axis=1)[:, 1:6]
        s = ann.settle(x[:64], x[near], x[1000:2000], 10**8, 0.95, 3)
        met = np.zeros((200, 3000), bool)
        for t in range(s.tables):
            own = ann.nearest_buckets(x, t, s, 1, 3)[:, 0]
            asked = ann.nearest_buckets(x[100:300], t, s, s.probes, 3)
            met |= (asked[:, :, None] == own[None, None, :]).any(1)
        best = np.argsort(-(x[100:300] @ x.T), axis=1)[:, 1:6]
        assert np.take_along_axis(met, best, 1).mean() >= 0.9
        share[name] = met.mean()
    assert share["groups"] < 0.1 and share["loose"] < 0.8


def test_many_blocks(spark, monkeypatch):
    monkeypatch.setattr(ann, "BLOCK", 64)
    e = table(spark, "/root/testdata/sf0.001", "embeddings")
    one = {(r.query_id, r.rank): r.vec_id for r in ann.search(e).collect()}
    monkeypatch.setattr(ann, "BLOCK", 4096)
    assert one == {(r.query_id, r.rank): r.vec_id for r in ann.search(e).collect()}


def test_hadamard_keeps_lengths():
    x = np.random.default_rng(1).normal(size=(5, 48))
    y = ann.rotate(x, 2, 3)
    assert y.shape == (5, 64) and np.allclose((y * y).sum(1), (x * x).sum(1))


def test_pipeline_stages(spark, sf):
    docs, stage = table(spark, sf, "documents"), Stage(spark, "test")
    before = docs.collect()
    for i, (name, step) in enumerate(corpus_pipeline.STAGES):
        out = stage.put(step(spark, docs, sf))
        after = out.collect()
        if i < 4:
            assert out.columns == docs.columns
        if i == 0:
            assert {r.doc_id for r in before} - {r.doc_id for r in after} == {r.doc_id for r in before if not any(c.isalpha() for c in r.text or "")}
        if i == 1:
            gone = brute_lines([(r.doc_id, r.text) for r in before])
            assert {r.doc_id: r.text for r in after} == {r.doc_id: "\n".join(x for k, x in enumerate(r.text.split("\n")) if k not in gone.get(r.doc_id, [])) for r in before}
        if i == 2:
            groups = brute_groups([(r.doc_id, r.text) for r in before], 80)
            assert {r.doc_id for r in after} == {d for d, (_, c) in groups.items() if c == d}
        if i == 3:
            words = sum(len(WORD.findall(r.text)) for r in before)
            assert abs(sum(len(WORD.findall(r.text)) for r in after) - 1.5 * words) < 0.1 * words
        docs, before = out, after
    assert len(before) == corpus_pipeline.run(spark, sf).count()


def test_mixed_and_unlabelled_documents_stay(spark):
    model = langid.Crf(list("abcdef"), np.zeros((langid.TABLE + 1, 6), np.float32), np.zeros(0, np.uint64), np.zeros((0, 6), np.float32), np.zeros((6, 6)), np.zeros(6))
    docs = spark.createDataFrame([(1, "one two three", None), (2, "123", None), (3, None, None), (4, "", None)], "doc_id long, text string, lang string")
    for m in (model, langid.learn(docs)):
        assert [r.doc_id for r in langid.drop_unidentified(docs, m).collect()] == [1]


def test_shared_and_missing_ids(spark):
    rows = [(None, "AAAAAAAAA\nunique line one"), (None, "unique line 222\nAAAAAAAAA"), (3, "BBBBBBBBB\nthird text"), (3, "something else\nBBBBBBBBB")]
    got = [r.text for r in lines.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()]
    kept = "\n".join(got)
    assert all(kept.count(x) == 1 for x in ("AAAAAAAAA", "BBBBBBBBB", "unique line one", "unique line 222", "third text", "something else"))

    a, b, c, d = (" ".join(f"{x}{i}" for i in range(40)) for x in "abcd")
    rows = [(1, a), (2, a), (2, b), (None, a + " more"), (None, c), (None, c), (None, c.upper()), (None, None), (None, ""), (None, d)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    left = [(r.doc_id, (r.text or "").lower()) for r in neardup.keep_one(df, 80).collect()]
    assert sorted(left, key=str) == sorted([(1, a), (2, b), (None, c), (None, ""), (None, ""), (None, d)], key=str)
    # near copies of one doc_id: one of the two stays, and so do texts of that id that are their own
    twins = spark.createDataFrame([(1, a), (1, a + " more"), (1, b), (1, b), (2, a)], "doc_id long, text string")
    left = [(r.doc_id, r.text) for r in neardup.keep_one(twins, 80).collect()]
    assert len(left) == 2 and (1, b) in left and {d for d, _ in left} == {1}
    report = {(r.n_shingles, r.component_id, r.kept) for r in neardup.near_duplicates(df, 80).where("doc_id is null").collect()}
    assert (37, 1, False) in report and (36, None, True) in report and (0, None, True) in report


def test_clusters_need_a_shared_folder():
    class Conf:
        get = staticmethod(lambda *a: None)

    class Session:
        conf = Conf

        class sparkContext:  # noqa: N801
            master = "spark://driver:7077"
            getConf = staticmethod(lambda: Conf)

    with pytest.raises(ValueError):
        shared_dir(Session)
    Session.sparkContext.master = "local[4]"
    assert shared_dir(Session)


def test_rejected_documents(spark):
    docs = spark.createDataFrame([(1, "the of and", "en"), (2, "123", "en"), (3, None, "en")], "doc_id long, text string, lang string")
    assert [r.doc_id for r in langid.drop_unidentified(docs, langid.learn(docs)).collect()] == [1]
