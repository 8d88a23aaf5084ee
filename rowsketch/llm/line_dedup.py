"""Line deduplication by winnowing over line hashes, with DataFrame functions only.

A text is a sequence of lines; a line is compared lower-cased and without the
white space around it, and
lines without a word are left out of account.  From every line on, the least
run of lines with ``min_words`` words is hashed (mostly one line).  A window
holds the runs that begin within ``min_words`` words; the least hash of each
window is selected, the last one on a tie.  A line of ``min_words`` words is a
window of its own, and two texts that share lines of twice as many words share
a whole window and so select the same place of it: a guaranteed fingerprint.

Each selected position is joined with the first position, in order of document
and line, that selected the same hash.  The two lie on a diagonal (document,
earlier document, shift); along it equal lines are extended both ways, and runs
of at least ``min_words`` words are deleted from the later place.  What was
first stays: a deleted line always has an equal line at an earlier place.
A hash may be selected first in another context than the one that two later
texts share, so the steps repeat on the lines that are left until nothing more
is found; then no line of ``min_words`` words, and no run of lines of twice as
many, occurs twice among the kept lines.

Large groups: only the first position of a hash is joined, never all pairs of
its positions, and minima are summed on the map side.  A document that very
many others repeat is joined with them by salt, once for each salt they have.
The rounds end, as each deletes lines; a chain in which each round's kept
lines bring up the next repeat takes a round a link.

Null texts stay null and have no lines; empty texts stay; equal rows are
documents of their own, the later ones lose their lines; a null id orders last;
an empty table gives an empty result; other columns pass through, whatever their
names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rowsketch.llm.common import WORD, free_name, named
from rowsketch.shared import discard, materialise

MIN_WORDS = 10
#: Parts that the documents repeating one other document are dealt in.
SALTS = 16
#: White space that is no line feed.
BLANKS = " \t\x0b\x0c\r"


def _lines(base: DataFrame, text: str, doc_id: str, row: str) -> DataFrame:
    """(doc, k, h, n): document order key, line number, hash and words of each line with a word."""
    parts = F.transform(F.split(named(text), "\n"), lambda line, i: F.struct(i.alias("k"), F.xxhash64(F.lower(F.btrim(line, F.lit(BLANKS)))).alias("h"), F.regexp_count(line, F.lit(WORD)).alias("n")))
    doc = F.struct(named(doc_id).isNull().alias("last"), named(doc_id).alias("id"), named(row).alias("row"))
    rows = base.select(doc.alias("doc"), F.explode(F.filter(parts, lambda x: x["n"] > 0)).alias("line"))
    return rows.select("doc", "line.*")


def _selected(lines: DataFrame, min_words: int) -> DataFrame:
    """(h, doc, r): the window minima; r is the place, among the document's lines, where the hashed run begins."""
    order = Window.partitionBy("doc").orderBy("k")
    placed = lines.select("*", F.row_number().over(order).alias("r"), (F.sum("n").over(order) - F.col("n")).alias("before"))
    ahead = Window.partitionBy("doc").orderBy("before").rangeBetween(0, min_words - 1)
    # the lines that begin before the run has its words are the run; the last runs of a document fall short
    runs = placed.select("doc", "r", "before", F.when(F.sum("n").over(ahead) >= min_words, F.xxhash64(F.collect_list("h").over(ahead))).alias("g"))
    least = runs.select("doc", F.min(F.when(F.col("g").isNotNull(), F.struct(F.col("g"), (-F.col("r")).alias("back")))).over(ahead).alias("m"))
    return least.where("m is not null").select(F.col("m.g").alias("h"), "doc", (-F.col("m.back")).alias("r")).distinct()


def _repeats(lines: DataFrame, min_words: int) -> DataFrame:
    """(doc, k) of the lines in runs that an earlier place has as well."""
    picked = materialise(_selected(lines, min_words), "picked")
    first = materialise(picked.groupBy("h").agg(F.min(F.struct("doc", "r")).alias("at"), F.count("*").alias("times")).where("times > 1").select("h", "at"), "first")
    pairs = picked.join(first, "h").where(F.struct("doc", "r") > F.col("at"))
    diagonals = materialise(pairs.select("doc", F.col("at.doc").alias("other"), (F.col("at.r") - F.col("r")).cast("int").alias("shift")).distinct(), "diagonals")
    # the lines of documents on a diagonal, in order
    wanted = diagonals.select("doc").unionByName(diagonals.select(F.col("other").alias("doc"))).distinct()
    whole = lines.join(wanted, "doc", "left_semi").groupBy("doc").agg(F.sort_array(F.collect_list(F.struct("k", "h", "n"))).alias("s"))
    whole = materialise(whole, "sequences")
    salt = F.pmod(F.xxhash64("doc"), F.lit(SALTS)).alias("salt")
    here = diagonals.select("*", salt).join(whole, "doc")
    wanted = diagonals.select("other", salt).distinct()
    both = here.join(whole.select(F.col("doc").alias("other"), F.col("s.h").alias("t")).join(wanted, "other"), ["other", "salt"])
    # places i (from 1) of the document whose line equals the earlier document's line at i + shift
    equal = F.expr("""
        filter(transform(sequence(greatest(1, 1 - shift), greatest(greatest(1, 1 - shift), least(size(s), size(t) - shift))),
                         i -> struct(i as i, try_element_at(s, i) as l, try_element_at(t, i + shift) as o)),
               x -> x.l.h = x.o)
    """)
    same = both.select("doc", "other", "shift", F.explode(equal).alias("x")).select("doc", "other", "shift", F.col("x.i").alias("i"), F.col("x.l.k").alias("k"), F.col("x.l.n").alias("n"))
    along = Window.partitionBy("doc", "other", "shift").orderBy("i")
    runs = same.select("*", (F.col("i") - F.row_number().over(along)).alias("run"))
    words = F.sum("n").over(Window.partitionBy("doc", "other", "shift", "run"))
    return runs.select("doc", "k", words.alias("words")).where(F.col("words") >= min_words).select("doc", "k").distinct()


def find_repeats(base: DataFrame, doc_id: str, row: str, *, min_words: int = MIN_WORDS, text: str = "text") -> DataFrame:
    """(doc, k) of all lines to delete from ``base``; ``row`` names a column that is unique."""
    lines = materialise(_lines(base, text, doc_id, row), "lines")
    found = None
    while True:
        gone = materialise(_repeats(lines, min_words), "repeats")
        if not gone.limit(1).count():
            break
        found = gone if found is None else found.unionByName(gone)
        before, lines = lines, materialise(lines.join(gone, ["doc", "k"], "left_anti"), "lines")
        discard(before)
    discard(lines)
    return gone if found is None else found


def dedup_lines(docs: DataFrame, *, min_words: int = MIN_WORDS, doc_id: str = "doc_id", text: str = "text", count: str | None = None) -> DataFrame:
    """The documents with later repeated runs of lines deleted from ``text``.

    ``count`` names an output column for the number of deleted lines; an input
    column of that name gives way to it.
    """
    names = [c for c in docs.columns if c != count]
    own, row, gone = (free_name(docs.columns, c) for c in ("dedup_id", "dedup_row", "dedup_gone"))
    base = materialise(docs.select(*[named(c) for c in names], named(doc_id).cast("long").alias(own), F.monotonically_increasing_id().alias(row)), "numbered")
    repeats = find_repeats(base, own, row, min_words=min_words, text=text)
    by_doc = materialise(repeats.groupBy(F.col("doc.row").alias(row)).agg(F.sort_array(F.collect_list(F.col("k").cast("int"))).alias(gone)), "deleted")
    # what is deleted grows with the input: a merge join at every size, so that no plan turns to broadcasting it
    joined = base.join(by_doc.hint("merge"), row, "left")
    lines, at = F.split(named(text), "\n"), F.col(gone)
    # stretches between deleted lines: (first line, how many)
    between = F.zip_with(F.concat(F.array(F.lit(-1)), at), F.concat(at, F.array(F.size(lines))), lambda a, b: F.struct((a + 1).alias("a"), (b - a - 1).alias("n")))
    left = F.array_join(F.flatten(F.transform(F.filter(between, lambda x: x["n"] > 0), lambda x: F.slice(lines, x["a"] + 1, x["n"]))), "\n")
    out = [F.when(at.isNull(), named(c)).otherwise(left).alias(c) if c == text else named(c) for c in names]
    if count:
        out.append(F.coalesce(F.size(at), F.lit(0)).cast("long").alias(count))
    return joined.select(*out)
