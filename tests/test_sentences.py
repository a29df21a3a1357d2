"""Sentences of more words than a part holds."""

from lexbridge.functions import text as X
from lexbridge.operators import attention as A
from lexbridge.plans.graph import GraphFrames


def test_long_sentences_keep_every_word_in_parts_of_their_own(spark):
    word = lambda i: "".join(chr(97 + int(c)) for c in f"{i:05d}")
    texts = [" ".join(map(word, range(n))) + ". one two three four. too short" for n in (4, 64, 65, 129, 3792, 3907)]
    docs = spark.createDataFrame([*enumerate(texts), (99, None), (100, "")], "doc_id long, text string")
    got = X.whole_words(docs).orderBy("doc_id", "sent_ix").collect()
    assert len({(r.doc_id, r.sent_ix) for r in got}) == len(got) and all(4 <= len(r.words) <= 64 for r in got)
    for d, text in enumerate(texts):
        assert [w for r in got if r.doc_id == d for w in r.words] == text.replace(".", "").split()[:-2]


def test_facts_of_long_sentences_are_weighed_part_by_part(spark, small):
    f = GraphFrames(spark, small)
    cut = X.sentence_words(f.docs.where("domain in ('N2', 'N3', 'N4')"), "domain")
    assert f.sents.selectExpr("sum(size(words))").first()[0] > cut.selectExpr("sum(size(words))").first()[0]
    rows = A.cooccurrence_rows(f.sents, f.pool_words)
    totals = rows.groupBy("domain", "doc_id", "sent_ix", "i").agg({"a": "sum", "j": "max"}).collect()
    assert totals and all(abs(r["sum(a)"] - 1) < 1e-9 and r["max(j)"] < 64 for r in totals)
