import zlib
from collections import Counter, defaultdict

import pytest

from semfilter.llm import interleave as I
from semfilter.llm import pivotal_mix as M


def docs(spark, n=700):
    rows = [(i, None if i % 97 == 0 else ("wörd " * (i % 23 + (400 if i % 101 == 0 else 0))), None if i % 50 == 3 else f"s{0 if i % 3 == 0 else i % 7}", i, "y") for i in range(n)]
    return rows, spark.createDataFrame(rows, "doc_id long, text string, source string, shard int, size string").repartition(5)


@pytest.mark.parametrize("shards", [1, 4, 16])
def test_shards_hold_the_mixture(spark, monkeypatch, shards):
    monkeypatch.setattr(I, "BUCKET_ROWS", 64)
    rows, df = docs(spark)
    got = I.interleave(df, shards).collect()
    text = {r[0]: r[1] for r in rows}
    by, mix = defaultdict(list), defaultdict(Counter)
    for r in got:
        by[r["shard"]].append(r["slot"])
        mix[r["source"]][r["shard"]] += 1
        t = (text[r["doc_id"]] or "").encode()
        assert (r["size"], r["text_crc32"]) == (len(t) + 1, zlib.crc32(t))
    assert len(got) == len(rows) and set(by) == set(range(shards))
    assert max(map(len, by.values())) - min(map(len, by.values())) <= 1
    assert all(sorted(s) == list(range(len(s))) for s in by.values())
    for c in mix.values():
        counts = [c[k] for k in range(shards)]
        assert max(counts) - min(counts) <= 2
    again = I.interleave(df.repartition(2), shards).collect()
    assert {(r["doc_id"], r["shard"], r["slot"]) for r in again} == {(r["doc_id"], r["shard"], r["slot"]) for r in got}


def test_shards_of_little(spark):
    _, df = docs(spark)
    assert I.interleave(df.limit(0)).count() == 0
    few = I.interleave(df.limit(3), 16).collect()
    assert [r["slot"] for r in few] == [0, 0, 0]
    same = spark.createDataFrame([(1, "a", "s")] * 40, "doc_id long, text string, source string")
    assert Counter(r["shard"] for r in I.interleave(same, 4).collect()) == Counter(dict.fromkeys(range(4), 10))


def filled(sizes, weights=(3, 1, 2), share=1.5, cap=2.0):
    names = sorted((s for s in sizes if s is not None), key=lambda s: [ord(c) for c in s]) + ([None] if None in sizes else [])
    w = {s: weights[k % 3] for k, s in enumerate(names)}
    left, open_, out = share * sum(sizes.values()), set(names), {}
    while open_:
        total = sum(w[s] for s in open_)
        over = {s for s in open_ if left * w[s] / total > cap * sizes[s]}
        if not over:
            out |= {s: left * w[s] / total for s in open_}
            break
        for s in over:
            out[s] = cap * sizes[s]
        left, open_ = left - sum(out[s] for s in over), open_ - over
    return out


def test_mix_meets_its_targets(spark, monkeypatch):
    monkeypatch.setattr(M, "FAN_BITS", 3)
    rows, df = docs(spark)
    got = M.mix(df).collect()
    assert len(got) == len(rows)
    sizes, taken, longest = Counter(), Counter(), Counter()
    for r in got:
        t = {x[0]: x[1] for x in rows}[r["id"]] or ""
        assert r["size"] == len(t.split()) and 0 <= r["copies"] * r["size"] <= 2 * r["size"]
        sizes[r["source"]] += r["size"]
        taken[r["source"]] += r["copies"] * r["size"]
        longest[r["source"]] = max(longest[r["source"]], r["size"])
    want = filled(sizes)
    for r in got:
        assert r["source_size"] == sizes[r["source"]] and abs(r["target"] - want[r["source"]]) < 1e-6
    for s in sizes:
        assert abs(taken[s] - want[s]) <= longest[s] / 2 + 1e-6
    assert sorted((r["id"], r["copies"]) for r in M.mix(df.repartition(2)).collect()) == sorted((r["id"], r["copies"]) for r in got)


def test_mix_keeps_chances(spark):
    df = spark.createDataFrame([(i, "w " * (5 + i % 4), f"s{i % 2}") for i in range(60)], "doc_id long, text string, source string")
    total = Counter()
    for seed in range(12):
        for r in M.mix(df, seed).collect():
            total[r["source"]] += r["copies"]
            total["all"] += 1
    goal = M.mix(df).select("source", "source_size", "target").distinct().collect()
    for g in goal:
        assert abs(total[g["source"]] / (12 * 30) - g["target"] / g["source_size"]) < 0.08


def test_mixed_documents_repeat_as_taken(spark):
    rows, df = docs(spark, 200)
    out = M.mixed_documents(df)
    assert out.columns == df.columns
    copies = {r["id"]: r["copies"] for r in M.mix(df).collect()}
    assert Counter(r["doc_id"] for r in out.collect()) == Counter({k: v for k, v in copies.items() if v})
    twice = spark.createDataFrame([(1, "a b", "s"), (1, "a b", "s"), (2, "c", "t")], "doc_id long, text string, source string")
    assert M.mixed_documents(twice).count() == sum(r["copies"] for r in M.mix(twice).collect())


def test_mix_of_nothing(spark):
    _, df = docs(spark)
    assert M.mix(df.limit(0)).count() == 0
    empty = spark.createDataFrame([(1, None, None), (2, "", "a")], "doc_id long, text string, source string")
    assert {(r["size"], r["target"]) for r in M.mix(empty).collect()} == {(0, 0.0)}
