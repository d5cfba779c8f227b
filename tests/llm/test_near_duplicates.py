import numpy as np
import pytest

from semfilter.llm import odd_sketch as K

RNG = np.random.default_rng(11)
WORDS = [f"w{i}" for i in range(3000)]


def text(n):
    return [WORDS[i] for i in RNG.integers(0, len(WORDS), n)]


def changed(words, k):
    out = list(words)
    for p in RNG.choice(len(out), k, replace=False):
        out[p] = WORDS[RNG.integers(0, len(WORDS))]
    return out


def corpus():
    base = [text(120) for _ in range(6)]
    rows = [" ".join(changed(b, int(k))) for b in base for k in RNG.integers(0, 12, 25)]
    rows += [" ".join(text(60)) for _ in range(60)] + ["A b  C", "a B c", "a b", "", "  \t", None, "one two three four five", "one two three four five six"]
    rows += [rows[0].upper().replace("W", "w"), rows[0].replace(" ", "\n"), rows[3], rows[3]]
    order = RNG.permutation(len(rows))
    return [(int(i), rows[k]) for i, k in enumerate(order)]


def brute(rows):
    sets = {}
    for i, t in rows:
        w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "").split()
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    comp = {i: i for i in sets}

    def find(i):
        while comp[i] != i:
            i = comp[i]
        return i

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b]:
                both = len(sets[a] & sets[b])
                if 100 * both >= 75 * (len(sets[a]) + len(sets[b]) - both):
                    x, y = find(a), find(b)
                    comp[max(x, y)] = min(x, y)
    return sets, {i: find(i) for i in ids}


@pytest.mark.parametrize("block", [5, 1024])
def test_equals_brute_force(spark, monkeypatch, block):
    monkeypatch.setattr(K, "BLOCK", block)
    rows = corpus()
    df = spark.createDataFrame([(i, t, 1, "z") for i, t in rows], "doc_id long, text string, n int, comp string").repartition(4)
    sets, comp = brute(rows)
    got = K.near_duplicates(df).collect()
    assert len(got) == len(rows)
    for r in got:
        assert (r["n_shingles"], r["component_id"], r["kept"]) == (len(sets[r["doc_id"]]), comp[r["doc_id"]], comp[r["doc_id"]] == r["doc_id"])
    kept = K.one_of_each(df)
    assert kept.columns == df.columns and {r["doc_id"] for r in kept.collect()} == {i for i, c in comp.items() if i == c}


def test_without_broadcast(spark, monkeypatch):
    monkeypatch.setattr(K, "BROADCAST_IDS", 3)
    rows = corpus()
    df = spark.createDataFrame(rows, "doc_id long, text string")
    _, comp = brute(rows)
    assert {r["doc_id"]: r["component_id"] for r in K.near_duplicates(df).collect()} == comp


def test_links_between_reaches_what_all_pairs_reach():
    base = text(100)
    texts = [" ".join(changed(base, int(k))) for k in RNG.integers(0, 25, 60)]
    sets = K.shingle_sets(texts, K.WordHashes())
    sig = K.signatures(sets)
    n, ids = np.array([len(s) for s in sets]), np.arange(60)
    links = K.links_between(ids, ids.copy(), n, K.odd_sketches(sig), sets, np.full(60, 2), K.most_odd_bits(0.75), 75)
    _, comp = brute(list(enumerate(texts)))
    seen = dict(enumerate(range(60)))
    for a, b in links:
        x, y = seen[a], seen[b]
        seen = {k: min(x, y) if v in (x, y) else v for k, v in seen.items()}
    assert seen == comp


def test_sketches_estimate_similarity():
    a = RNG.integers(0, 2**63, 1000).astype(np.uint64)
    for share in (0.95, 0.85, 0.75):
        m = int(1000 * 2 * share / (1 + share))
        pair = [np.unique(a), np.unique(np.concatenate([a[:m], RNG.integers(0, 2**63, 1000 - m).astype(np.uint64)]))]
        odd = K.odd_sketches(K.signatures(pair)).view(np.uint8)
        bits = int(np.unpackbits(odd[0] ^ odd[1]).sum())
        assert abs(K.estimate(bits) - share) < 0.15 and bits <= K.most_odd_bits(0.75)


def test_odd_tables(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert K.near_duplicates(empty).count() == 0 and K.one_of_each(empty).count() == 0
    odd = spark.createDataFrame([(None, "a b c"), (1, None), (1, "a b c"), (1, "a b c"), (2, "A B C")], "doc_id long, text string")
    got = {(r["doc_id"], r["component_id"]) for r in K.near_duplicates(odd).collect()}
    assert got == {(None, None), (1, 1), (2, 1)}
    assert sorted((r["doc_id"] or 0, r["text"]) for r in K.one_of_each(odd).collect() if r["text"]) == [(0, "a b c"), (1, "a b c")]
    assert K.one_of_each(odd).filter("text IS NULL").count() == 1


def test_an_id_with_several_texts(spark):
    """All texts of an id take part; near_duplicates joins them to one component, one_of_each keeps unlike ones."""
    a, b, lone = text(80), text(80), text(40)
    rows = [(5, " ".join(a)), (5, " ".join(b)), (6, " ".join([*a, "x"])), (7, " ".join([*b, "y"])), (8, " ".join(lone)), (8, " ".join(lone)), (8, None), (3, " ".join(lone)), (9, "")]
    df = spark.createDataFrame([(i, t, i, "q") for i, t in rows], "doc_id long, text string, id int, k string").repartition(3)
    got = K.near_duplicates(df).toPandas()
    assert len(got) == len(rows)
    assert dict(zip(got["doc_id"], got["component_id"], strict=True)) == {5: 5, 6: 5, 7: 5, 8: 3, 3: 3, 9: 9}
    assert set(got.loc[got["kept"], "doc_id"]) == {5, 3, 9}
    kept = K.one_of_each(df)
    assert kept.columns == df.columns
    assert sorted((r["doc_id"], r["text"] or "") for r in kept.collect()) == sorted([(5, " ".join(a)), (5, " ".join(b)), (3, " ".join(lone)), (8, ""), (9, "")])


def test_very_long_texts_and_small_blocks(spark, monkeypatch):
    monkeypatch.setattr(K, "BLOCK_SHINGLES", 500)
    long = text(150_000)
    near = changed(long, 1500)
    rows = [(1, " ".join(long)), (2, " ".join(near)), (3, " ".join(long[:60_000])), (4, "x" * 500_000), (5, "x " * 100_000), (6, "x " * 50_000), *((10 + i, t) for i, t in corpus())]
    sets, comp = brute(rows)
    got = K.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect()
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == {i: (len(sets[i]), comp[i]) for i, _ in rows}
    assert comp[2] == 1 and comp[3] == 3 and comp[6] == 5
