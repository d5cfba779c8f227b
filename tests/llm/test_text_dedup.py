import random
from collections import defaultdict

import pytest

from semfilter.llm import line_spread as L
from semfilter.llm import span_dedup as S


def lines_table():
    rows = []
    for i in range(120):
        own = f"own line {i}"
        t = [own, " shared everywhere " if i % 2 else "shared everywhere"]
        if i < 10:
            t.append("on ten sites")
        if i < 9:
            t.append("on nine sites")
        if i % 12 == 0:
            t += ["hot", "hot", ""]
        rows.append((i, None if i == 77 else "\n".join(t), None if i == 5 else f"s{i % 12}", "x"))
    return rows + [(200, "", "s1", "x"), (201, "\n\n", "s2", "x"), (3, rows[3][1], "s3", "x")]


def want_lines(rows, least, keep_first):
    sites, seen = defaultdict(set), defaultdict(list)
    for d, t, s, _ in rows:
        for p, line in enumerate((t or "").split("\n")):
            if line.strip(" "):
                sites[line.strip(" ")].add(("=" + s) if s is not None else "")
                seen[line.strip(" ")].append((d, p))
    out = []
    for d, t, _, _ in rows:
        if t is None:
            out.append((d, None, 0, 0))
            continue
        parts = t.split("\n")
        gone = {p for p, x in enumerate(parts) if x.strip(" ") and len(sites[x.strip(" ")]) >= least and not (keep_first and (d, p) == min(seen[x.strip(" ")]))}
        out.append((d, "\n".join(x for p, x in enumerate(parts) if p not in gone), sum(bool(x.strip(" ")) for x in parts), len(gone)))
    return sorted(out, key=str)


@pytest.mark.parametrize("keep_first", [True, False])
def test_lines_equal_brute_force(spark, keep_first):
    rows = lines_table()
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, pos string").repartition(4)
    out = L.spread_lines(df, 10, keep_first=keep_first)
    got = sorted(((r["doc_id"], r["text"], r["_n_lines"], r["_n_removed"]) for r in out.collect()), key=str)
    assert got == want_lines(rows, 10, keep_first)
    assert out.columns == [*df.columns, "_n_lines", "_n_removed"]


def test_near_threshold_lines_are_counted_exactly(spark):
    rows = [(i, "wide", f"site{i}") for i in range(60)] + [(100 + i, "narrow", f"site{i}") for i in range(49)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    found = L.boilerplate(L.lines_of(df), 50, lg_k=4)
    assert [r["n"] for r in found.collect()] == [60]


def test_no_lines(spark):
    assert L.spread_lines(spark.createDataFrame([], "doc_id long, text string, source string")).count() == 0


PASSAGE = " ".join(f"pass{i}" + (". And" if i % 7 == 6 else "") for i in range(60)) + "."
FLAT = " ".join(f"flat{i}" for i in range(70))


def test_sentences_rejoin_and_cut_alike():
    for t in (PASSAGE, FLAT, "A 3.14 b. C!\n\nD? e", "...", "", "\n", "x" * 500, "a.b.c d", "Q. W. " * 40):
        starts, counts, hashes = S.sentences(t)
        ends = [*starts[1:], len(t)]
        assert not starts or starts[0] == 0
        assert not starts or "".join(t[a:b] for a, b in zip(starts, ends, strict=True)) == t
        assert sum(counts) == len(t.split()) and len(hashes) == len(counts)
    inside = set(S.sentences(f"some words {FLAT} and more")[2])
    assert len(inside & set(S.sentences(f"{FLAT} other words follow here")[2])) >= 4


def span_words(text):
    _, a, b = S.spans(*S.cut(text)[1:])
    return set(zip(a.tolist(), b.tolist(), strict=True))


@pytest.mark.parametrize("stops", [0, 0.04, 0.1, 0.3])
def test_every_passage_of_51_words_meets(stops):
    rng = random.Random(f"passages {stops}")

    def words(n, stops, vocabulary):
        return " ".join(f"w{rng.randrange(vocabulary)}" + rng.choice([".", "!", "?\n"]) * (rng.random() < stops) for _ in range(n))

    for _ in range(1500):
        passage = words(51, stops, rng.choice([2, 20, 10**6]))
        a, b = (" ".join([words(rng.randrange(40), s, 10**6), passage, words(rng.randrange(40), s, 10**6)]).strip() for s in (rng.choice([0, 0.1, 0.5]) for _ in "ab"))
        assert span_words(a) & span_words(b), (passage, a, b)


def test_short_repeats_stay():
    line = "one two three four five six seven. Eight nine ten eleven twelve."
    assert not span_words(f"Before it. {line} Afterwards.") & span_words(f"Ahead of this. {line} Others follow.")
    line = "One two. A sentence of nine words is cut here. So."
    assert span_words(f"Before it.\n{line}\nAfterwards.") & span_words(f"Ahead of this.\n{line}\nOthers follow.")


def brute_spans(rows):
    owner, own = {}, {}
    for d, t in rows:
        if t and d is not None:
            starts, counts, hashes = S.sentences(t)
            own[d] = []
            for k in range(len(counts)):
                e = next((e for e in range(k + S.SENTENCES, len(counts) + 1) if sum(counts[k:e]) >= S.SPAN_WORDS), None)
                if e is not None:
                    own[d].append((k, tuple(hashes[k:e])))
            for _, h in own[d]:
                owner[h] = min(owner.get(h, d), d)
    out = {}
    for d, t in rows:
        if not t or d is None:
            out[d] = (t, 0)
            continue
        seen, gone = set(), []
        for k, h in own[d]:
            if h in seen or owner[h] != d:
                gone.append(k)
            seen.add(h)
        out[d] = S.cleaned(t, gone) if gone else (t, 0)
    return out


@pytest.mark.parametrize("few", [500_000, 1])
def test_spans_equal_brute_force(spark, monkeypatch, few):
    monkeypatch.setattr(S, "BROADCAST_IDS", few)
    rows = [(i, f"Start number {i} is here. " + (PASSAGE if i % 3 == 0 else FLAT if i % 3 == 1 else "") + f" End of document {i}, nothing else follows. Bye {i}.") for i in range(40)]
    shout = " ".join(f"W{k}!!" for k in range(30))
    rows += [(70, f"One more. {shout} So."), (71, f"Another one. {shout} Thus.")]
    rows += [(50, None), (51, ""), (52, "Short."), (53, f"{PASSAGE} Between {PASSAGE} After."), (None, PASSAGE), (60, rows[2][1]), (61, rows[2][1])]
    df = spark.createDataFrame([(d, t, 1) for d, t in rows], "doc_id long, text string, at int").repartition(4)
    got = {r["doc_id"]: (r["text"], r["n_removed"]) for r in S.without_repeats(df).collect()}
    assert got == brute_spans(rows)
    assert got[0][1] == 0 and got[60][0] == "" and "pass30" not in got[3][0] and "Start number 3" in got[3][0]
    assert "W9!!" in got[70][0] and "W9!!" not in got[71][0] and "Another one" in got[71][0]
    assert "flat30" not in got[4][0] and got[53][0].count("pass30") == 0


def test_no_spans(spark):
    assert S.without_repeats(spark.createDataFrame([], "doc_id long, text string")).count() == 0
