"""Line dedup (operator 10), by winnowing over line hashes, in DataFrame operations only.

A document is the sequence of its non-blank lines, trimmed. Of every ``window`` consecutive lines the line of the least hash is selected,
the first of equal ones, so any run of at least ``window`` lines that occurs twice has a selected line at the same place of it; a long
line is a run by itself and is selected too. These (document, position) minima are the fingerprints. Those whose hash stands at one
position in the whole corpus end there. The others are joined by position: a match is extended from the fingerprint to the left and to
the right over the lines that must agree for a run, under each of the places that the fingerprint can have in it, and the content reached that way is
matched with the first place, in order of id and line, where it stands. Extensions that overlap in a document are one run, as long as the lines agree;
every line of a run that stands earlier elsewhere, or earlier in its own document, is deleted.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lexbridge.llm.scratch import Scratch, fresh, join_counted, small


def _least_at(i: Column, window: int) -> Column:
    """The position of the least hash of the window that begins at ``i``."""
    own = F.slice("hs", i, window)
    return (i + F.array_position(own, F.array_min(own)) - 1).cast("int")


def fingerprints(docs: DataFrame, window: int, long_line: int, scratch: Scratch) -> tuple[DataFrame, DataFrame]:
    """The documents' line hashes (doc_id, mark, hs, nos, long) and the selected minima (doc_id, mark, j, h), j from 1."""
    lines = F.split(F.col("text"), "\n", -1)
    solid = F.filter(F.transform(lines, lambda x, i: F.struct(i.alias("no"), F.trim(F.translate(x, "\t\r\f\x0b", "    ")).alias("x"))), lambda s: s.x != "")
    hashed = F.transform(solid, lambda s: F.struct(s.no.alias("no"), F.xxhash64(s.x).alias("h"), (F.length(s.x) >= long_line).alias("long")))
    own = docs.where("text is not null").select("doc_id", F.xxhash64("text").alias("mark"), hashed.alias("ls"))
    own = own.select("doc_id", "mark", F.col("ls.h").alias("hs"), F.col("ls.no").alias("nos"), F.col("ls.long").alias("long"))
    own = scratch.keep(own.where((F.size("hs") >= window) | F.exists("long", lambda x: x)), "own")
    windows = F.when(F.size("hs") >= window, F.sequence(F.lit(1), F.size("hs") - (window - 1))).otherwise(F.array().cast("array<int>"))
    alone = F.filter(F.transform("long", lambda x, i: F.when(x, i + 1)), lambda x: x.isNotNull())
    selected = F.array_distinct(F.concat(F.transform(windows, lambda i: _least_at(i, window)), alone))
    rows = own.select("doc_id", "mark", F.inline(F.transform(selected, lambda j: F.struct(j.alias("j"), F.element_at("hs", j).alias("h")))))
    return own, scratch.keep(rows, "prints")


def repeated_lines(docs: DataFrame, window: int, long_line: int, scratch: Scratch) -> DataFrame:
    """doc_id, mark (hash of the text), gone (numbers of the lines to delete, from 0): documents that lose lines only."""
    own, prints = fingerprints(docs, window, long_line, scratch)
    again = scratch.keep(prints.groupBy("h").agg(F.count("*").alias("c")).where("c > 1"), "again")
    seeds = join_counted(prints, again, "h", "c").groupBy("doc_id", "mark").agg(F.collect_set("j").alias("js"))
    seeds = scratch.keep(seeds.select(F.col("doc_id").alias("_id"), F.col("mark").alias("_mark"), "js"), "seeds")
    same = F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("mark") == F.col("_mark"))
    near = own.dropDuplicates(["doc_id", "mark"]).join(small(seeds, "2 + size(js)"), same).drop("_id", "_mark")
    # a fingerprint is the least of some windows round it; each of them is an extension that another place can share
    begins = F.filter(F.sequence(F.greatest(F.lit(1), F.col("j") - (window - 1)), F.col("j")), lambda i: (i + (window - 1) <= F.size("hs")) & (_least_at(i, window) == F.col("j")))
    spans = F.transform(begins, lambda i: F.struct(i.alias("i"), F.lit(window).alias("n"), F.xxhash64(F.slice("hs", i, window)).alias("body")))
    alone = F.when(F.element_at("long", F.col("j")), F.array(F.struct(F.col("j").alias("i"), F.lit(1).alias("n"), F.xxhash64(F.element_at("hs", F.col("j"))).alias("body")))).otherwise(F.array().cast("array<struct<i:int,n:int,body:bigint>>"))
    spread = near.select("doc_id", "mark", "hs", "long", F.explode("js").alias("j")).select("doc_id", "mark", F.inline(F.concat(spans, alone)))
    spread = scratch.keep(spread, "extended")
    place = F.struct("doc_id", "mark", "i")
    first = scratch.keep(spread.groupBy("body").agg(F.min(place).alias("first"), F.count("*").alias("c")).where("c > 1"), "first")
    later = join_counted(spread, first, "body", "c").where(place > F.col("first"))
    hits = later.groupBy(F.col("doc_id").alias("_id"), F.col("mark").alias("_mark")).agg(F.collect_set(F.struct("i", "n")).alias("runs"))
    hits = scratch.keep(hits, "hits")
    hit = own.select("doc_id", "mark", "nos").dropDuplicates(["doc_id", "mark"]).join(small(hits, "2 + 2 * size(runs)"), same)
    covered = F.array_distinct(F.flatten(F.transform("runs", lambda r: F.slice("nos", r.i, r.n))))
    return hit.select("doc_id", "mark", covered.alias("gone"))


def dedup_lines(docs: DataFrame, window: int = 3, long_line: int = 60, names: tuple[str, str] = ("n_lines", "n_deleted")) -> DataFrame:
    """Deletes later repeats of runs of ``window`` or more lines, and of single lines of at least ``long_line`` characters.

    Keeps every input column and row, with the shortened ``text``, and adds the counts of lines and of deleted ones under ``names``; an input
    column of such a name is replaced. A null text stays null with no lines; an empty text is one blank line. Blank lines stay, as do shorter
    repeated lines outside such runs. Rows repeated with the same id and text are one document and come back alike; rows of one id with different texts are
    documents of their own, in the order of a hash of the text.
    """
    scratch = Scratch(docs.sparkSession, "lines")
    gone = repeated_lines(docs.select("doc_id", "text"), window, long_line, scratch)
    docs = docs.drop(*names)
    i, m, g = fresh(docs, "lost_id", "lost_mark", "lost")
    gone = scratch.keep(gone.select(F.col("doc_id").alias(i), F.col("mark").alias(m), F.col("gone").alias(g)), "gone")
    scratch.only("gone")
    # one form at every size: the numbers of deleted lines grow with the corpus, so a broadcast would only do for small ones
    cut = docs.join(gone.hint("merge"), docs["doc_id"].eqNullSafe(F.col(i)) & (F.xxhash64(docs["text"]) == F.col(m)), "left")
    text, lost = docs["text"], F.col(g)
    lines = F.split(text, "\n", -1)
    kept = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), lost)
    short = F.when(lost.isNull(), text).otherwise(F.array_join(F.transform(kept, lambda k: F.get(lines, k)), "\n"))
    n_lines = F.when(text.isNull(), 0).otherwise(F.size(lines)).alias(names[0])
    n_gone = F.when(lost.isNull(), 0).otherwise(F.size(lost)).alias(names[1])
    return cut.select(*[short.alias(c) if c.lower() == "text" else docs[c] for c in docs.columns], n_lines, n_gone)


ORACLE = r"""
WITH l AS (SELECT doc_id, generate_subscripts(string_split(text, chr(10)), 1) - 1 AS no, unnest(string_split(text, chr(10))) AS x FROM documents),
s AS (SELECT doc_id, no, trim(translate(x, chr(9) || chr(13) || chr(12) || chr(11), '    '), ' ') AS x FROM l),
n AS (SELECT doc_id, no, x, row_number() OVER (PARTITION BY doc_id ORDER BY no) AS i FROM s WHERE x <> ''),
w AS (SELECT a.doc_id, a.i, a.x AS x1, b.x AS x2, c.x AS x3 FROM n a JOIN n b ON a.doc_id = b.doc_id AND b.i = a.i + 1 JOIN n c ON a.doc_id = c.doc_id AND c.i = a.i + 2),
r AS (SELECT doc_id, i, row_number() OVER (PARTITION BY x1, x2, x3 ORDER BY doc_id, i) AS k FROM w),
o AS (SELECT doc_id, no, row_number() OVER (PARTITION BY x ORDER BY doc_id, i) AS k FROM n WHERE length(x) >= 60),
g AS (SELECT DISTINCT n.doc_id, n.no FROM n JOIN r ON n.doc_id = r.doc_id AND n.i BETWEEN r.i AND r.i + 2 WHERE r.k > 1
      UNION SELECT doc_id, no FROM o WHERE k > 1),
k AS (SELECT l.doc_id, string_agg(CASE WHEN g.no IS NULL THEN x END, chr(10) ORDER BY l.no) AS text, count(*)::INTEGER AS n_lines, count(g.no)::INTEGER AS n_deleted
      FROM l LEFT JOIN g ON l.doc_id = g.doc_id AND l.no = g.no GROUP BY l.doc_id)
SELECT d.doc_id, CASE WHEN d.text IS NULL THEN NULL ELSE coalesce(k.text, '') END AS text, d.lang, d.source, d.n_chars, coalesce(k.n_lines, 0)::INTEGER AS n_lines, coalesce(k.n_deleted, 0)::INTEGER AS n_deleted
FROM documents d LEFT JOIN k ON d.doc_id = k.doc_id
"""
