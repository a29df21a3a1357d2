"""The dealt operators on small fixtures: brute force, and every odd case of the inputs."""

import random
import re
from collections import defaultdict

import numpy as np
import pyarrow as pa
import pytest

from lexbridge.llm import queries as Q
from lexbridge.llm import tokens
from lexbridge.llm.decontaminate import Settings, common_words, find_leaks
from lexbridge.llm.embedding_dedup import hadamard, near_duplicate_vectors
from lexbridge.llm.graph import components
from lexbridge.llm.jaccard_join import link_components
from lexbridge.llm.language_id import language_report
from lexbridge.llm.line_dedup import dedup_lines, fingerprints
from lexbridge.llm.mixing import mix_sources
from lexbridge.llm.passage_dedup import compact_windows, repeated_passages
from lexbridge.llm.pii import _luhn, find_pii, find_spans, mask_pii
from lexbridge.llm.scratch import Scratch
from lexbridge.llm.toxicity import toxicity_report
from lexbridge.llm.url_filter import judge_urls
from tests.oracle import check

DOCS = "doc_id long, text string, lang string, source string, n_chars long, component_id string, score int"
SMALL = "/root/testdata/sf0.001"


def words_of(text):
    return re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in every column, empty and long texts, ties and repeated rows, and columns with names that operators add."""
    rng = random.Random(5)
    vocabulary = ["w" + str(i) for i in range(400)]
    prose = lambda n: " ".join(rng.choice(vocabulary) for _ in range(n))
    base = prose(120)
    near = base.split()
    near[60] = "changed"
    rows = [
        (1, base, "en", "a", 1), (2, base, "en", None, 2), (3, " ".join(near), None, "b", 3), (4, None, "en", "a", None), (5, "", "en", "b", 0), (6, "  \n ", "de", "b", 4),
        (7, "one two", "de", "a", 7), (8, "one two", "de", "c", 7), (9, prose(30_000), "en", "a", 9), (10, "A@B.co +1 (437) 555-0689", "en", "a", 5),
        (11, prose(80) + "\n" + "\n".join(["x y z", "p q r", "s t u", "v w x"]), "de", "a", 1), (12, prose(80) + "\n" + "\n".join(["x y z", "p q r", "s t u", "v w x"]), "de", "b", 1),
        (None, base, "en", "a", 1), (13, "same row", "en", "a", 8), (13, "same row", "en", "a", 8),
    ]
    return spark.createDataFrame([(*r, "c", 0) for r in rows], DOCS)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def brute_components(rows):
    sets = {}
    for d, text in rows:
        w = words_of(text)
        sets[d] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    up = {d: d for d in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            inter = len(sets[a] & sets[b])
            if inter and 100 * inter >= 75 * len(sets[a] | sets[b]):
                x, y = root(a), root(b)
                up[max(x, y)] = min(x, y)
    return {d: (len(sets[d]), root(d)) for d in sets}


def test_jaccard_join_equals_brute_force(spark):
    df = spark.read.parquet(f"{SMALL}/documents.parquet")
    want = brute_components([(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()])
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in link_components(df).collect()} == want


def test_jaccard_join_of_a_large_group_of_near_copies(spark):
    rng = random.Random(2)
    base = [f"b{i}" for i in range(60)]
    rows = []
    for d in range(60):
        w = list(base)
        for _ in range(rng.randint(0, 2)):
            w[rng.randrange(60)] = f"e{d}{rng.randrange(9)}"
        rows.append((d, " ".join(w)))
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in link_components(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == brute_components(rows)


def test_jaccard_join_of_ids_with_several_texts(spark):
    rng = random.Random(3)
    a, b = ([f"w{rng.randrange(10**6)}" for _ in range(40)] for _ in range(2))
    rows = [(1, " ".join(a)), (2, " ".join(a)), (2, " ".join(b)), (3, " ".join([*b[:-1], "else"])), (4, "by itself"), (5, ""), (5, "two words"), (5, "two words"), (None, " ".join(a))]
    got = sorted((r.doc_id or 0, r.component_id or 0) for r in link_components(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == [(0, 0), (1, 1), (2, 1), (2, 1), (3, 1), (4, 4), (5, 5), (5, 5), (5, 5)]


def test_jaccard_join_of_odd_rows(odd, empty):
    got = link_components(odd).collect()
    assert len(got) == odd.count() and link_components(empty).count() == 0
    by = {r.doc_id: r for r in got}
    assert by[1].component_id == by[2].component_id == by[3].component_id == 1
    assert by[4].n_shingles == by[5].n_shingles == by[6].n_shingles == 0 and by[5].component_id == 5
    assert by[8].component_id == 7 and by[None].component_id is None


def test_components_of_a_path_and_beyond_the_bound(spark, monkeypatch):
    from lexbridge.llm import graph

    edges = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101)], "a long, b long")
    for bound in (10_000, 0):
        monkeypatch.setattr(graph, "ONE_TASK_EDGES", bound)
        got = {r.node: r.comp for r in components(edges, "a", "b", Scratch(spark, "t"), f"c{bound}").collect()}
        assert got == {**dict.fromkeys(range(41), 0), 100: 100, 101: 100}


def test_word_and_shingle_sets():
    texts = [None, "", " a ", "A b\tc d E f", "x" * 2_000_000 + " y", "é É ß z"]
    got = []
    for a, b, w, bounds, _ in tokens.documents_of(pa.record_batch({"text": pa.array(texts)})):
        s, ends = tokens.shingle_hashes(w, bounds)
        got += [(int(bounds[i + 1] - bounds[i]), len(np.unique(s[ends[i] : ends[i + 1]]))) for i in range(b - a)]
    want = [len(words_of(t)) for t in texts]
    assert [g[0] for g in got] == want and [g[1] for g in got] == [0, 0, 1, 2, 1, 1]


def test_compact_windows_equal_the_recursive_tree():
    rng = np.random.default_rng(0)
    for turn in range(60):
        bounds = np.concatenate(([0], np.cumsum(rng.integers(0, 90, size=4))))
        v = rng.integers(0, 40 if turn % 2 else 1 << 60, size=bounds[-1]).astype(np.uint64)
        t = int(rng.integers(2, 20))
        want = set()

        def cut(lo, hi):
            if hi - lo + 1 >= t:
                c = lo + int(np.argmin(v[lo : hi + 1]))
                want.add((lo, c, hi))
                cut(lo, c - 1)
                cut(c + 1, hi)

        for i in range(4):
            cut(bounds[i], bounds[i + 1] - 1)
        assert set(zip(*[x.tolist() for x in compact_windows(v, bounds, t)], strict=True)) == want


def test_repeated_passages_are_all_covered(spark):
    rng = random.Random(3)
    prose = lambda n: [f"w{rng.randrange(5000)}" for _ in range(n)]
    passage = prose(60)
    rows = [(i, " ".join(prose(rng.randint(0, 200)) + (passage if i % 2 else []) + prose(rng.randint(0, 200)))) for i in range(30)]
    got = repeated_passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {r.doc_id for r in got} == {i for i in range(30) if i % 2}
    texts = dict(rows)
    for r in got:
        assert " ".join(passage) in " ".join(texts[r.doc_id].split()[max(0, r.start_word - 15) : r.end_word + 15])


def test_repeated_passages_of_odd_rows(odd, empty):
    got = repeated_passages(odd)
    assert {1, 2, 3} <= {r.doc_id for r in got.collect()} and repeated_passages(empty).count() == 0


def test_mixing(spark, odd, empty):
    check(spark, Q.QUERIES["op2_mix_sources"], Q.ORACLES["op2_mix_sources"], SMALL)
    got = mix_sources(odd).collect()
    assert len(got) == odd.count() and mix_sources(empty).count() == 0
    assert all(0 <= r.taken <= 3 * r.size for r in got) and sum(r.taken for r in got) <= sum(r.size for r in got)
    assert sorted(map(str, got)) == sorted(map(str, mix_sources(odd.repartition(7)).collect()))


def test_mixing_of_texts_without_words(spark):
    rows = [(1, None, "a"), (2, "", "a"), (3, " \n", None), (None, "", "b")]
    got = mix_sources(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    assert len(got) == 4 and all(r["size"] == r.source_size == r.taken == r.copies == 0 and r.target == 0 for r in got)


def test_line_dedup(spark, odd, empty):
    check(spark, Q.QUERIES["op10_line_dedup"], Q.ORACLES["op10_line_dedup"], SMALL)
    got = dedup_lines(odd).collect()
    assert len(got) == odd.count() and dedup_lines(empty).count() == 0
    by = {r.doc_id: r for r in got}
    assert by[12].n_deleted == 4 and by[11].n_deleted == 0 and "x y z" not in by[12].text and by[4].text is None and by[5].text == ""


def test_lines_without_repeats_keep_no_fingerprint(spark):
    rng = random.Random(8)
    rows = [(d, "\n".join(f"line {rng.randrange(10**12)}" for _ in range(40))) for d in range(50)]
    own, prints = fingerprints(spark.createDataFrame(rows, "doc_id long, text string"), 3, 60, Scratch(spark, "t"))
    assert own.count() == 50 and 0.4 < prints.count() / 2000 < 0.65 and prints.groupBy("h").count().where("count > 1").count() == 0


def test_line_runs_equal_brute_force(spark):
    rng = random.Random(6)
    for long_line in (7, 1000):
        docs = [(d, "\n".join(rng.choice(["a", "b", "c", " d ", "", "longest"]) for _ in range(rng.randint(0, 9)))) for d in range(60)]
        seen, want = set(), {}
        for d, text in docs:
            lines = text.split("\n")
            solid = [(i, x.strip()) for i, x in enumerate(lines) if x.strip()]
            gone = set()
            for n in (1, 3):
                for i in range(len(solid) - n + 1):
                    body = tuple(x for _, x in solid[i : i + n])
                    if n == 3 or len(body[0]) >= long_line:
                        if body in seen:
                            gone |= {no for no, _ in solid[i : i + n]}
                        seen.add(body)
            want[d] = "\n".join(x for i, x in enumerate(lines) if i not in gone)
        got = {r.doc_id: r.text for r in dedup_lines(spark.createDataFrame(docs, "doc_id long, text string"), long_line=long_line).collect()}
        assert got == want


def test_line_dedup_with_clashing_columns(spark):
    names = ["n_lines", "n_deleted", "gone", "lost", "lost_id", "_lost", "mark", "_mark", "_id", "nos"]
    rows = [(d, "p\nq\nr\ns", *range(len(names))) for d in (1, 2)]
    got = {r.doc_id: r for r in dedup_lines(spark.createDataFrame(rows, ["doc_id", "text", *names])).collect()}
    assert got[1].n_deleted == 0 and got[2].n_deleted == 4 and got[2].n_lines == 4 and got[2].gone == 2 and got[2].lost == 3 and got[2].nos == 9


def test_pii_equals_the_patterns():
    kinds = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
    digits = lambda s: re.sub("[^0-9]", "", s)
    good = {"email": lambda s: True, "ip": lambda s: all(int(p) <= 255 for p in s.split(".")), "card": lambda s: 16 <= len(digits(s)) <= 19 and _luhn(digits(s)), "phone": lambda s: 8 <= len(digits(s)) <= 15}
    rng = random.Random(1)
    for _ in range(20_000):
        alphabet = rng.choice(["0123456789 -", "01.+() -9", "a@.b-_1", "a@b.1+ ()2-", "25.16", "é1+ 2@x.y"])
        text = "".join(rng.choice(alphabet) for _ in range(rng.randint(0, 45)))
        want = {k: [m.span() for m in re.finditer(p, text) if good[k](m[0])] for k, p in kinds.items()}
        found = find_spans(text)
        assert {k: found.get(k, []) for k in kinds} == want, text


def test_pii_of_odd_rows(odd, empty):
    got = {r.doc_id: r for r in find_pii(odd).collect()}
    assert got[10].n_email == 1 and got[10].n_phone == 1 and got[10].spans == "email:0:6,phone:7:24"
    assert got[4].spans == "" and got[4].base_sha256 == got[5].base_sha256 and find_pii(empty).count() == 0
    assert {r.doc_id: r.text for r in mask_pii(odd.select("doc_id", "text")).collect()}[10] == "****** *****************"
    assert "account:8:30" in str([f"{k}:{a}:{b}" for k, v in find_spans("My IBAN DE89370400440532013000 is").items() for a, b in v])


def test_language_id(spark, odd, empty):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = language_report(df, per_label=150).join(df.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert np.mean([r.lang == r.lang_pred for r in got]) > 0.95 and all(0 <= r.score <= 1 for r in got)
    by = {r.doc_id: r for r in language_report(odd).collect()}
    assert len(by) == 14 and by[4].lang_pred == by[5].lang_pred == by[6].lang_pred == "und" and by[1].lang_pred != "und"
    assert language_report(empty).count() == 0


def test_toxicity(spark, odd, empty):
    rng = random.Random(7)
    rows, labels = [], []
    for d in range(400):
        toxic = d % 4 == 0
        sentences = [" ".join(f"w{rng.randrange(200)}" for _ in range(8)) for _ in range(4)]
        if toxic:
            sentences[2] += " stupid"
        rows.append((d, ". ".join(sentences)))
        labels.append((d, int(toxic)))
    docs, known = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")
    got = [r for r in toxicity_report(docs, known).collect() if r.held_out]
    truth = dict(labels)
    assert np.mean([r.predicted == truth[r.doc_id] for r in got]) > 0.9
    assert np.mean([r.worst_sentence == 2 for r in got if truth[r.doc_id]]) > 0.9
    nothing = spark.createDataFrame([], "doc_id long, toxic int, score string")
    by = toxicity_report(odd, nothing).collect()
    assert len(by) == odd.count() and all(0 <= r.score <= 1 for r in by) and toxicity_report(empty, known).count() == 0


def test_longest_common_subsequence():
    rng = random.Random(4)
    for _ in range(200):
        a, b = ([rng.randrange(6) for _ in range(rng.randint(1, 20))] for _ in range(2))
        bits = defaultdict(int)
        for i, w in enumerate(a):
            bits[w] |= 1 << i
        row = [0] * (len(b) + 1)
        for x in a:
            last = 0
            for j, y in enumerate(b):
                last, row[j + 1] = row[j + 1], last + 1 if x == y else max(row[j + 1], row[j])
        assert common_words(dict(bits), len(a), b) == row[-1]


def test_leaks(spark, odd, empty):
    rng = random.Random(9)
    prose = lambda n: [f"w{int(rng.paretovariate(0.6)) % 3000}" for _ in range(n)]
    items = [(i, " ".join(prose(40))) for i in range(12)]
    rows = [(d, " ".join(prose(rng.randint(20, 300)))) for d in range(150)]
    for i, text in items:
        w = text.split()
        w[7] = w[21] = "other"
        rows[i * 3] = (i * 3, " ".join(prose(50)) + " " + (text if i % 2 else " ".join(w)) + " " + " ".join(prose(50)))
    docs, bench = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    s = Settings(rank=64, common=1)
    got = {(r.doc_id, r.item_id) for r in find_leaks(docs, bench, s).collect()}
    assert got == {(i * 3, i) for i in range(12)}
    blocks = {(r.doc_id, r.item_id) for r in find_leaks(docs, bench, Settings(rank=64, common=1, query_block=5)).collect()}
    assert blocks == got
    none = spark.createDataFrame([(1, None), (None, "x y"), (2, "")], "item_id long, text string")
    assert find_leaks(odd, none).count() == 0 and find_leaks(empty, bench).count() == 0 and find_leaks(docs, bench.limit(0)).count() == 0


def test_embeddings(spark):
    rng = np.random.default_rng(0)
    centres = rng.standard_normal((30, 64))
    rows = [(i, (centres[i % 30] + 0.15 * rng.standard_normal(64)).tolist(), int(i % 30 % 3)) for i in range(400)]
    rows += [(1000, rows[0][1], 0), (1001, rows[0][1], None), (1002, None, 0), (1003, [0.0] * 64, 0), (1004, [float("nan")] * 64, 0), (1005, [1.0, None], 0), (1006, [], 0), (1007, [2.0], 0), (1008, [4.0], 0)]
    got = {r.vec_id: r for r in near_duplicate_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")).collect()}
    assert len(got) == len(rows)
    x = {v: np.array(e) / np.linalg.norm(e) for v, e, _ in rows[:401]}
    label = {v: y for v, _, y in rows}
    true = {v: sum(1 for u in x if u != v and label[u] == label[v] and x[u] @ x[v] >= 0.93) for v in x}
    assert sum(got[v].n_links for v in x) >= 0.9 * sum(true.values()) and all(got[v].n_links <= true[v] for v in x)
    for v in (1001, 1002, 1003, 1004, 1005, 1006):
        assert got[v].n_links == 0 and got[v].component_id == v and got[v].kept
    assert got[1000].n_links >= 1 and not got[1000].kept and got[1008].component_id == 1007
    assert near_duplicate_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>, label int")).count() == 0


def test_hadamard_keeps_lengths_up_to_scale():
    x = np.random.default_rng(0).standard_normal((5, 16))
    assert np.allclose((hadamard(x) ** 2).sum(axis=1), 16 * (x**2).sum(axis=1))


def test_urls(spark):
    rows = [
        (1, "http://a.example.NET/en/1?x", "a.example.net", "/en/1", "example.net/en/", "allow"), (2, "http://b.net/x", "b.net", "/x", "net/", "block"),
        (3, "https://example.com/de/9#t", "example.com", "/de/9", "example.com/de/", "block"), (4, "https://q.org/fr/", "q.org", "/fr/", "org/fr/", "allow"),
        (5, "http://notexample.com/de/1", "notexample.com", "/de/1", None, None), (6, "no scheme", "", "", None, None), (7, None, "", "", None, None),
        (8, "http://b.net", "b.net", "", None, None), (9, "http://b.net?u=http://c.org/fr/", "b.net", "", None, None), (10, "http://poker-slots.test/casino", "poker-slots.test", "/casino", None, "block"), (11, "http://village-school.test/en/books", "village-school.test", "/en/books", None, "allow"),
    ]
    got = {r.page_id: r for r in judge_urls(spark.createDataFrame([(r[0], r[1], "x") for r in rows], "page_id long, url string, host string")).collect()}
    for page, _, host, path, rule, verdict in rows:
        assert (got[page].host, got[page].path, got[page].rule) == (host, path, rule)
        assert got[page].verdict in ("allow", "block") and (verdict is None or got[page].verdict == verdict)
    assert judge_urls(spark.createDataFrame([], "page_id long, url string")).count() == 0


def test_deleted_lines_meet_their_texts_in_one_form_at_every_size(spark):
    from lexbridge.llm.line_dedup import dedup_lines

    docs = spark.createDataFrame([(i, "a b c\nd e f\ng h i\n" + str(i)) for i in range(4)] + [(None, None)], "doc_id long, text string")
    out = dedup_lines(docs)
    assert "BroadcastHashJoin" not in out._jdf.queryExecution().executedPlan().toString()
    assert sorted(r.n_deleted for r in out.collect()) == [0, 0, 3, 3, 3]


def test_toxicity_is_learned_in_a_task_not_in_the_driver(spark, monkeypatch):
    import os

    from lexbridge.llm import toxicity

    rows = [(d, "plain words here. " + ("awful stuff." if d % 2 else "nice day.")) for d in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    known = spark.createDataFrame([(d, d % 2) for d in range(60)], "doc_id long, toxic int")
    monkeypatch.setattr(toxicity, "_fit", lambda bags, y, *_: toxicity.ToxicModel(np.array([len(bags), sum(y)], np.float32), float(os.getpid())))
    model = toxicity.fit_toxicity(docs, known)
    assert model.bias != os.getpid() and model.weights[0] > model.weights[1] > 0
