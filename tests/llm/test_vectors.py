import numpy as np
import pytest

from semfilter.llm import tile_links as L
from semfilter.llm import topk_blocks as K

RNG = np.random.default_rng(3)


def frame(spark, rows):
    return spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int, seg string").repartition(3)


def odd_rows():
    v = RNG.normal(size=(130, 8)).astype(np.float32)
    rows = [(i, v[i].tolist(), i % 3, "x") for i in range(120)]
    rows += [(200, None, 0, "x"), (201, [1.0, None] + [0.0] * 6, 0, "x"), (202, [float("nan")] * 8, 0, "x"), (203, [float("inf")] + [0.0] * 7, 0, "x"), (204, [0.0] * 8, 0, "x"), (250, [0.5] * 8, None, "x")]
    rows += [(300 + k, (v[0] * (1 + k) + 0.01 * k).tolist(), 0, "x") for k in range(5)] + [(400, v[1].tolist(), 2, "x"), (50, v[50].tolist(), 50 % 3, "x")]
    return rows


def usable(e):
    return e is not None and all(x is not None and np.isfinite(x) for x in e)


def brute_top(rows, k=5):
    """Every row against every row, in Python's integers: (rank, id, score) by query."""
    good = [(i, [int(np.floor(256 * x)) for x in np.array(e, np.float32).astype(float).tolist()]) for i, e, *_ in rows if usable(e) and len(e)]
    asks = {}
    for i, t in good:
        if i % 50 == 0:
            asks[i] = min(asks.get(i, t), t)
    out = {}
    for q, t in asks.items():
        best = sorted((-sum(a * b for a, b in zip(t, u, strict=True)), i) for i, u in good if i != q and len(u) == len(t))[:k]
        out[q] = [(n + 1, i, -s) for n, (s, i) in enumerate(best)]
    return {q: v for q, v in out.items() if v}


def top(spark, rows, parts=3):
    got = {}
    for r in K.top_k(frame(spark, rows).repartition(parts)).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    return {q: sorted(v) for q, v in got.items()}


@pytest.mark.parametrize(("block", "segment", "queries"), [(2, 16, 2), (64, 8192, 256)])
def test_top_k_equals_brute_force(spark, monkeypatch, block, segment, queries):
    monkeypatch.setattr(K, "BLOCK", block)
    monkeypatch.setattr(K, "SEGMENT", segment)
    monkeypatch.setattr(K, "QUERIES", queries)
    rows = [*odd_rows(), (60, [], 0, "x"), (50, [0.25] * 8, 0, "x"), (150, [1.0, 2.0], 0, "x"), (151, [3.0, 1.0], 0, "x")]
    assert top(spark, rows) == brute_top(rows)


def test_repeated_vectors_fill_several_ranks(spark):
    rows = [(0, [1.0, 0.0], 0, "x"), *[(7, [1.0, 0.0], 0, "x")] * 8, *[(i, [0.5, 0.1 * i], 0, "x") for i in range(1, 6)], *[(50, [0.0, 1.0], 0, "x")] * 3, (50, [0.0, 2.0], 0, "x")]
    assert top(spark, rows) == brute_top(rows) and [i for _, i, _ in top(spark, rows)[0]] == [7] * 5


def test_very_large_components(spark):
    big = 3.0e12
    rows = [(0, [big, big, -big], 0, "x"), (1, [big, 1.0, 2.0], 0, "x"), (2, [-big, 1.0, -big], 0, "x"), (3, [big, 1.0, 0.5], 0, "x"), (4, [1.0, 1.0, 1.0], 0, "x")]
    want = {q: [(n, i, min(K.MOST, max(K.LEAST, s))) for n, i, s in v] for q, v in brute_top(rows).items()}
    got = top(spark, rows)
    assert [s for *_, s in got[0]] == [s for *_, s in want[0]]


def test_kth_score_prunes_other_segments(spark, monkeypatch):
    monkeypatch.setattr(K, "BLOCK", 8)
    monkeypatch.setattr(K, "SEGMENT", 64)
    rng = np.random.default_rng(9)
    rows = [(i, (np.eye(8)[i // 100 % 8] + 0.05 * rng.normal(size=8)).tolist(), 0, "x") for i in range(800)]
    assert top(spark, rows) == brute_top(rows)
    got = K.pruning(frame(spark, rows)).toPandas()
    assert len(got) == 16 and (got["scored"] < got["blocks"] / 2).all() and (got["blocks"] >= 100).all()


def test_nothing_is_gathered_for_a_broadcast_and_queries_meet_few_rows(spark, monkeypatch):
    """What reaches the driver must not grow with the table, nor queries be written once for each segment."""
    monkeypatch.setattr(K, "SEGMENT", 16)
    monkeypatch.setattr(K, "SPREAD", 1, raising=False)
    rng = np.random.default_rng(5)
    rows = [(i, rng.normal(size=4).tolist(), 0, "x") for i in range(5000)]
    plans, dealt, save = [], [], K.save

    def seen(df, tag):
        plans.append(df._jdf.queryExecution().executedPlan().toString())
        got = save(df, tag)
        if tag == "index":
            dealt.append(got.count())
        return got

    monkeypatch.setattr(K, "save", seen)
    out = K.top_k(frame(spark, rows))
    got = {}
    for r in out.collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    assert {q: sorted(v) for q, v in got.items()} == brute_top(rows) and dealt[0] > 64
    plans.append(out._jdf.queryExecution().executedPlan().toString())
    assert not any("BroadcastExchange" in p for p in plans) and any("SortMergeJoin" in p for p in plans)


@pytest.mark.parametrize("most", [100, 1 << 20, 1 << 28, 1 << 40])
def test_sums_are_exact_in_every_kind_of_number(most):
    rng = np.random.default_rng(most % 97)
    docs, asked, ids = rng.integers(-most, most, (700, 4)), rng.integers(-most, most, (9, 4)), np.arange(700)
    kinds = {100: np.float32, 1 << 20: np.float64, 1 << 28: np.int64, 1 << 40: object}
    assert K._kind(asked, docs) is kinds[most]
    found, _ = K.search_segment(ids, docs, np.arange(9), asked, 5)
    for q in range(9):
        best = sorted((-sum(int(a) * int(b) for a, b in zip(asked[q], docs[i], strict=True)), i) for i in range(700) if i != q)[:5]
        assert [(i, s) for o, i, s in found if o == q] == [(i, min(K.MOST, max(K.LEAST, -s))) for s, i in best]


def test_bounds_skip_blocks():
    docs = np.sort(RNG.integers(-300, 300, (4096, 1)), axis=0) * np.ones((1, 4), int)
    found, scored = K.search_segment(np.arange(4096), docs, np.array([-1]), np.array([[1, 1, 1, 1]]), 5)
    assert [s for _, _, s in found] == sorted((docs.sum(axis=1)).tolist(), reverse=True)[:5]
    assert scored < 4096 / K.BLOCK / 2


def test_top_k_edges(spark):
    assert K.top_k(frame(spark, [])).count() == 0
    one = K.top_k(frame(spark, [(0, [1.0, 2.0], 0, "x"), (1, [1.0, 1.0], 0, "x"), (2, [1.0, 1.0], 0, "x")])).collect()
    assert [(r["rank"], r["vec_id"]) for r in sorted(one, key=lambda r: r["rank"])] == [(1, 1), (2, 2)]


def brute_links(rows, threshold):
    ok = [(i, np.array(e, np.float32).astype(float), l) for i, e, l, _ in rows if usable(e) and l is not None and any(e)]
    links = {i: set() for i, *_ in rows}
    for i, u, a in ok:
        for j, v, b in ok:
            if i != j and a == b and u @ v / (np.linalg.norm(u) * np.linalg.norm(v)) >= threshold:
                links[i].add(j)
    comp = {}
    for i in sorted(links):
        if i not in comp:
            todo = [i]
            while todo:
                k = todo.pop()
                if k not in comp:
                    comp[k] = i
                    todo += links[k]
    return links, comp


@pytest.mark.parametrize("block", [7, 2048])
def test_links_equal_brute_force(spark, monkeypatch, block):
    monkeypatch.setattr(L, "BLOCK", block)
    rows = [r for r in odd_rows() if r != odd_rows()[-1]]
    rows = [r for k, r in enumerate(rows) if r[0] not in {x[0] for x in rows[:k]}]
    links, comp = brute_links(rows, 0.8)
    got = L.near_vectors(frame(spark, rows), 0.8).collect()
    assert len(got) == len(rows)
    for r in got:
        assert (r["n_links"], r["component_id"], r["kept"]) == (len(links[r["vec_id"]]), comp[r["vec_id"]], comp[r["vec_id"]] == r["vec_id"])


def test_bounds_are_rigorous():
    u = RNG.normal(size=(300, 64))
    u /= np.linalg.norm(u, axis=1, keepdims=True)
    q, s, stood, miss = L.quantise(u)
    gap = np.abs(u @ u.T - L.code_products(q, q) * s[:, None] * s[None, :])
    assert (gap <= stood[:, None] * miss[None, :] + miss[:, None] * stood[None, :] + miss[:, None] * miss[None, :] + 1e-6).all()
    near = u[:50] + 0.15 * RNG.normal(size=(50, 64)) / 8
    i, j, asked = L.tile(u, near, 0.93)
    cos = (u @ near.T) / np.linalg.norm(near, axis=1)
    assert set(zip(i.tolist(), j.tolist(), strict=True)) == set(zip(*map(list, np.nonzero(cos >= 0.93)), strict=True))
    assert asked < cos.size / 10


def test_links_of_nothing(spark):
    assert L.near_vectors(frame(spark, [])).count() == 0
    lone = L.near_vectors(frame(spark, [(1, None, None, "x"), (2, None, 3, "x")])).collect()
    assert {(r["vec_id"], r["n_links"], r["component_id"], r["kept"]) for r in lone} == {(1, 0, 1, True), (2, 0, 2, True)}
