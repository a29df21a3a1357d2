"""Edited copies of passages, against brute force over all stretches."""

import random

import numpy as np
import pyarrow as pa

from lexbridge.llm import passage_dedup as P
from lexbridge.llm import tokens
from lexbridge.llm.passage_dedup import SHINGLE, _alike, _chained, _filed, _refiled, _shingles, _stretch_hashes, repeated_passages

SIZES = (50, 55, 60, 70, 80)


def shingles(words):
    return np.array([hash(tuple(words[i : i + SHINGLE])) & 0xFFFFFFFF for i in range(len(words) - SHINGLE + 1)], np.uint32)


def jaccard(x, y):
    a, b = set(x.tolist()), set(y.tolist())
    return len(a & b) / len(a | b)


def stands(x, y, t, shift):
    """Whether any stretch of t or more is alike, by brute force over starts and ends, with all small moves of the other end."""
    for b in range(len(x) - t + 1):
        for e in range(b + t, len(x) + 1):
            for more in (-1, 0, 1):
                lo, hi = b + shift, e + shift + more
                if 0 <= lo and hi <= len(y) and hi - lo >= t and jaccard(x[b:e], y[lo:hi]) >= 0.75:
                    return True
    return False


def edited(rng, size, place, kind):
    prose = lambda n: [rng.randrange(10**9) for _ in range(n)]
    p = prose(size)
    q = p[:place] + {"change": prose(1), "insert": [*prose(1), p[place]], "delete": []}[kind] + p[place + 1 :]
    return prose(12) + p + prose(12), prose(12) + q + prose(12)


def test_one_word_edits_at_every_place_equal_brute_force():
    rng, t = random.Random(0), 50 - SHINGLE + 1
    for size in SIZES:
        for place in range(size):
            for kind in ("change", "insert", "delete"):
                x, y = (shingles(w) for w in edited(rng, size, place, kind))
                got = _alike(x, y, t, 0.75)
                assert all(min(e - b, ye - yb) >= t and abs(jaccard(x[b:e], y[yb:ye]) - j) < 1e-12 and j >= 0.75 for b, e, yb, ye, j in got)
                assert got or not stands(x, y, t, 0), (size, place, kind)
                assert got or kind != "change"


def test_unlike_stretches_are_not_told():
    rng, t = random.Random(1), 50 - SHINGLE + 1
    for changes, alike in (((25,), True), ((10, 25, 40), False), ((5, 15, 25, 35, 45), False)):
        x, y = edited(rng, 50, 25, "change")
        for c in changes:
            y[12 + c] = rng.randrange(10**9)
        assert bool(_alike(shingles(x), shingles(y), t, 0.75)) == alike == stands(shingles(x), shingles(y), t, 0)


def test_edited_passages_are_repeated_passages(spark):
    rng = random.Random(1)
    rows = []
    for size in (50, 60, 80):
        for place in range(0, size, 5):
            x, y = edited(rng, size, place, "change")
            rows += [(len(rows), " ".join(map(str, x))), (len(rows) + 1, " ".join(map(str, y)))]
    got = {(r.doc_id, r.other_id) for r in repeated_passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    found = sum((d, d + 1) in got for d in range(0, len(rows), 2))
    assert found >= len(rows) // 2 - 1 and all(a // 2 == b // 2 for a, b in got)


def test_a_shorter_part_in_between_does_not_part_equal_passages(spark):
    rng = random.Random(2)
    prose = lambda n: [f"w{rng.randrange(10**6)}" for _ in range(n)]
    rows = []
    for _ in range(250):
        p = prose(50)
        rows += [(len(rows) + i, " ".join(prose(rng.randint(20, 150)) + x + prose(rng.randint(20, 150)))) for i, x in enumerate((p, p[:38], p))]
    got = {(r.doc_id, r.other_id) for r in repeated_passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all({(d, d + 2), (d + 2, d)} <= got for d in range(0, len(rows), 3)) and all(b - a in (-2, 2) for a, b in got)


def test_every_occurrence_in_a_document_is_told(spark):
    rng = random.Random(4)
    prose = lambda n: [f"w{rng.randrange(10**6)}" for _ in range(n)]
    p = prose(60)
    rows = [(1, prose(100) + p + prose(40)), (2, prose(60) + p + prose(140) + p + prose(90)), (3, prose(30) + p + prose(120) + p + prose(100) + p)]
    got = repeated_passages(spark.createDataFrame([(d, " ".join(w)) for d, w in rows], "doc_id long, text string")).collect()
    for d, w in rows:
        for at in [i for i in range(len(w)) if w[i : i + 60] == p]:
            assert any(r.doc_id == d and r.start_word <= at + 5 and r.end_word >= at + 55 for r in got), (d, at)


def test_stretch_hashes_equal_a_plain_loop():
    s = np.random.default_rng(1).integers(0, 2**64, 200, dtype=np.uint64)
    for t in (1, 2, 3, 45, 46, 47, 64, 200):
        plain = s[: len(s) - t + 1].copy()
        for j in range(1, t):
            plain = plain * np.uint64(0x9E3779B97F4A7C15) + s[j : len(s) - t + 1 + j]
        assert (plain == _stretch_hashes(s, t)).all()


def test_every_stretch_is_filed_again_once():
    rng, t = random.Random(5), 50 - SHINGLE + 1
    texts = [" ".join(f"w{rng.randrange(10**6)}" for _ in range(n)) for n in (300, 20, 50, 120)]
    batch = pa.record_batch([pa.array(range(10, 14)), pa.array(texts)], names=["doc_id", "text"])
    own = {d: set() for d in range(10, 14)}
    for b in _filed(t)(iter([batch])):
        for g, d in zip(b.column("g").to_pylist(), b.column("d").to_pylist(), strict=True):
            own[d].add(g)
    asked = batch.append_column("signatures", pa.array([sorted(v) for v in own.values()], pa.list_(pa.int64())))
    rows = [r for b in _refiled(t)(iter([asked])) for r in b.to_pylist()]
    for _, _, s, ends, _ in _shingles(batch):
        for i in range(len(texts)):
            x = s[ends[i] : ends[i + 1]]
            keys = tokens.mix(_stretch_hashes(x, t)).view(np.int64).tolist() if len(x) >= t else []
            for place, key in enumerate(keys):
                (r,) = [r for r in rows if r["g"] == key]
                assert r["d"] == 10 + i and r["c"] == place and 0 <= r["l"] <= place and place + t - 1 <= r["r"] < len(x)


def test_chains_do_not_depend_on_batches():
    rng = np.random.default_rng(0)
    rows = sorted({(int(a), int(b), int(c)) for a, b, c in rng.integers(0, (6, 4, 50), size=(150, 3))})
    table = pa.table({"g": [x[0] for x in rows], "d": [x[1] for x in rows], "l": pa.array([x[2] - 1 for x in rows], pa.int32()), "c": pa.array([x[2] for x in rows], pa.int32()), "r": pa.array([x[2] + 1 for x in rows], pa.int32())})
    want = None
    for size in (1, 2, 7, 1000):
        got = sorted(r for b in _chained(iter(table.to_batches(max_chunksize=size))) for r in zip(*[c.to_pylist() for c in b.columns], strict=True))
        want = want or got
        assert got == want
    partners = {(g, a) for g, a, *_ in want} | {(g, b) for g, _, b, *_ in want}
    assert partners == {(g, d) for g, d, _ in rows if len({y for x, y, _ in rows if x == g}) > 1}
    assert len(want) >= len(rows) - len({(g, d) for g, d, _ in rows})


def test_all_places_of_a_passage_are_of_one_class(spark):
    rng = random.Random(7)
    prose = lambda n: [f"w{rng.randrange(10**6)}" for _ in range(n)]
    p, q = prose(120), prose(90)
    rows = []
    for d in range(5):  # each pair of these differs in two words and is alike
        near = [*p]
        near[20 * d + 10] = f"x{d}"
        rows.append((d, " ".join(prose(40) + near + prose(30) + (q if d in (1, 4) else prose(20)) + prose(25))))
    got = repeated_passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    of = lambda low, high: {(r.doc_id, r.class_doc, r.class_start) for r in got if low <= r.start_word < high}
    first, second = of(0, 150), of(150, 400)
    assert {d for d, *_ in first} == set(range(5)) and len({c[1:] for c in first}) == 1 and {c[1] for c in first} == {0}
    assert {d for d, *_ in second} == {1, 4} and {c[1] for c in second} == {1} and len({c[1:] for c in second}) == 1


def test_second_filing_moves_texts_alike_at_every_size(spark, monkeypatch):
    words = [f"w{i}" for i in range(400)]
    same = " ".join(words[:60])
    texts = [f"{' '.join(f'{x}{d}' for x in words[60 : 90 + d])} {same} {' '.join(f'{d}{x}' for x in words[200:260])}" for d in range(5)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    seen = []
    chain = P._chain
    monkeypatch.setattr(P, "_chain", lambda filed: seen.append(filed) or chain(filed))
    P.repeated_passages(docs).collect()
    plan = seen[1]._jdf.queryExecution().optimizedPlan().toString()
    top = plan[plan.index("MapInArrow") :].splitlines()
    join = next(x for x in top if "Join Inner" in x)
    assert "Hint" not in join and "broadcast" not in join and any("LeftSemi" in x for x in top)


def test_signatures_of_a_document_do_not_depend_on_its_neighbours():
    draw = random.Random(5)
    texts = [" ".join(f"v{draw.randrange(10**6)}" for _ in range(n)) for n in (120, 3, 70, 260)]
    filed = lambda ids: sorted(tuple(r.values()) for b in _filed(46)(iter([pa.record_batch([pa.array(ids), pa.array([texts[i] for i in ids])], names=["doc_id", "text"])])) for r in b.to_pylist())
    assert filed([0, 1, 2, 3]) == sorted(filed([3, 0]) + filed([2, 1]))
