"""Operator 5: removal of repeated runs of lines, by prefix doubling over sequences of line ids.

A document is the sequence of its lines with a word; blank lines keep their place and take no part. A run of
consecutive lines that equals one at an earlier place (by doc_id, text hash and line) and has WORDS words or more is a
later copy and goes; each run needs the words by itself, so runs with different first places aren't added up.

1. Doubling: level 0 names each line by its hash, level k + 1 names 2 ** (k + 1) lines by the names of their
   halves. A place stays on a level only while its name occurs more than once there: the suffixes that
   start at the places of one name are an interval with a common prefix of 2 ** k lines.
2. Intervals: a depth between two powers is named by two overlapping runs of the lower power. For each line the
   shortest run from it on, and the shortest up to it, with enough words are looked up; the first place of an
   interval stays, the others are later copies of a run as long as the interval's common prefix.
3. Maximal runs: later copies of one document's lines at one distance join to maximal repeated runs.

The suffixes are sorted as far as WORDS lines. Nothing depends on more: each line of a longer repeated run lies in
its shortest beginning with enough words or in the shortest window that ends there, and since every line has a word,
neither has more than WORDS lines; both are repeated with the run, and repeated windows are such runs themselves.

Only DataFrame functions are used. Names are counted by partial aggregates; a name that many places have meets them
by a broadcast of a bounded number of names (operators/skew.py), so no line, however common, is one task's burden.

Cases: null text counts as empty and stays null; a text without lines with words is unchanged; a text whose lines all go
becomes empty; lines are equal if all their characters are; rows with equal doc_id are told apart by the hash of
their text, and of rows alike in both the copies count as one document; rows with a null doc_id come
before all others; an empty table gives no rows. All columns of the input are carried in one struct, so no name of theirs can clash.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from neardup.operators.skew import join_counted, repeated
from neardup.session import materialize, release

#: A run is deleted only where it has so many words at least.
WORDS = 10
_WORD = r"[^\x20\x09-\x0D]+"
_PLACE = ("d", "t", "at")


def _doc_key() -> list[Column]:
    return [F.coalesce("doc_id", F.lit(-(1 << 62))).alias("d"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("t")]


def _n_words(line: Column) -> Column:
    return F.size(F.regexp_extract_all(line, F.lit(_WORD), F.lit(0)))


def _bound(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value), with value made once for each row: an expression inside a lambda would be made for each element."""
    return F.transform(F.array(value), body)[0]


def line_sequences(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """Rows (d, t, at, name, check, ahead, behind, total): the lines with a word of distinct (doc_id, text), numbered without the blank ones.

    ahead and behind are the numbers of lines of the shortest run from a line on, and up to it, with so many words; 0 where there is none. total counts the document's words.
    """
    parts = F.transform(F.split(F.coalesce("text", F.lit("")), "\n", -1), lambda x: F.struct(F.xxhash64(x).alias("name"), F.xxhash64(F.lit(1), x).alias("check"), _n_words(x).alias("words")))

    def shortest(part: Column) -> Column:
        def step(acc: Column, x: Column) -> Column:
            return F.when(acc.w >= words, acc).otherwise(F.struct((acc.w + x.words).alias("w"), (acc.n + 1).alias("n")))

        return F.aggregate(part, F.struct(F.lit(0).alias("w"), F.lit(0).alias("n")), step, lambda acc: F.when(acc.w >= words, acc.n).otherwise(0))

    def around(lines: Column) -> Column:
        def of(x: Column, i: Column) -> Column:
            ahead = shortest(F.slice(lines, i + 1, F.lit(words)))
            behind = shortest(F.reverse(F.slice(lines, F.greatest(i + 2 - words, F.lit(1)), F.least(i + 1, F.lit(words)))))
            enough = x.words >= words
            return F.struct(x["name"].alias("name"), x["check"].alias("check"), F.when(enough, 1).otherwise(ahead).alias("ahead"), F.when(enough, 1).otherwise(behind).alias("behind"))

        return F.transform(lines, of)

    total = lambda lines: F.aggregate(lines, F.lit(0), lambda a, x: a + x.words)
    found = _bound(F.filter(parts, lambda x: x.words > 0), lambda lines: F.struct(around(lines).alias("lines"), total(lines).alias("total")))
    rows = docs.select(*_doc_key(), found.alias("doc")).select("d", "t", "doc.total", F.posexplode("doc.lines").alias("at", "x"))
    rows = rows.select("d", "t", "at", "x.name", "x.check", "x.ahead", "x.behind", "total")
    return rows.dropDuplicates(list(_PLACE))


def doubled(sequences: DataFrame, most_lines: int) -> list[DataFrame]:
    """Levels of rows (d, t, at, name, check): the places whose 2 ** level lines occur more than once, as far as most_lines lines."""
    levels = [materialize(repeated(sequences.select(*_PLACE, "name", "check"), ["name", "check"]), "level-0")]
    shift = 1
    while 2 * shift <= most_lines:
        rows = levels[-1]
        ahead = rows.select("d", "t", (F.col("at") - shift).alias("at"), F.col("name").alias("name2"), F.col("check").alias("check2"))
        both = rows.join(ahead, list(_PLACE)).select(*_PLACE, F.xxhash64("name", "name2").alias("name"), F.xxhash64("check2", "check").alias("check"))
        both = materialize(both, "doubled")
        levels.append(materialize(repeated(both, ["name", "check"]), f"level-{len(levels)}"))
        release(both)
        shift *= 2
    return levels


def later_copies(sequences: DataFrame, levels: list[DataFrame]) -> tuple[list[DataFrame], DataFrame]:
    """Written tables, and from them rows (d, t, at, n, fd, ft, words, far): n lines from at on equal those at the first place of their interval, far lines before in (fd, ft), which has so many words."""
    runs = F.array(F.struct("at", F.col("ahead").alias("n")), F.struct((F.col("at") - F.col("behind") + 1).alias("at"), F.col("behind").alias("n")))
    wanted = sequences.select("d", "t", "total", F.explode(F.array_distinct(F.filter(runs, lambda x: x.n > 0))).alias("x")).select("d", "t", "x.at", "x.n", "total")
    found = None
    for k, level in enumerate(levels):
        power = 1 << k
        here = wanted.where((F.col("n") >= power) & (F.col("n") < 2 * power)).join(level, list(_PLACE))
        exact = here.where(F.col("n") == power).select(*_PLACE, "total", "n", "name", "check")
        tail = level.select("d", "t", F.col("at").alias("tail"), F.col("name").alias("name2"), F.col("check").alias("check2"))
        between = here.where(F.col("n") > power).withColumn("tail", F.col("at") + F.col("n") - power).join(tail, ["d", "t", "tail"])
        both = exact.unionByName(between.select(*_PLACE, "total", "n", F.xxhash64("n", "name", "name2").alias("name"), F.xxhash64("check2", "n", "check").alias("check"))) if power > 1 else exact
        found = both if found is None else found.unionByName(both)
    found = materialize(found, "runs")
    place = F.struct(*_PLACE, "total")
    intervals = found.groupBy("n", "name", "check").agg(F.min(place).alias("first"), F.max(place).alias("last"), F.count("*").alias("rows")).where("first <> last")
    intervals = materialize(intervals.select("n", "name", "check", "first", "rows"), "intervals")
    copies = join_counted(found, intervals, ["n", "name", "check"], n="rows").where(place != F.col("first"))
    return [found, intervals], copies.select(*_PLACE, "n", F.col("first.d").alias("fd"), F.col("first.t").alias("ft"), F.col("first.total").alias("words"), (F.col("at") - F.col("first.at")).alias("far"))


def maximal_runs(copies: DataFrame) -> DataFrame:
    """One row (d, t, sources) for each document: for the document of each first place its words and the runs (at, end) of lines, as long as they go at one distance."""
    chain = ("d", "t", "fd", "ft", "words", "far")
    spans = copies.select(*chain, "at", (F.col("at") + F.col("n")).alias("end")).distinct()
    order = Window.partitionBy(*chain).orderBy("at", "end")
    reached = F.max("end").over(order.rowsBetween(Window.unboundedPreceding, -1))
    islands = spans.withColumn("new", F.when(F.col("at") <= reached, 0).otherwise(1)).withColumn("island", F.sum("new").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    runs = islands.groupBy(*chain, "island").agg(F.min("at").alias("at"), F.max("end").alias("end"))
    per_source = runs.groupBy("d", "t", "fd", "ft", "words").agg(F.collect_list(F.struct("at", "end")).alias("runs"))
    return per_source.groupBy("d", "t").agg(F.collect_list(F.struct("runs", "words")).alias("sources"))


def _cut(docs: DataFrame, words: int, version_share: float | None) -> DataFrame:
    """Rows (row, text, n_removed, n_runs): all columns of docs as a struct, and the text without its later copies."""
    sequences = materialize(line_sequences(docs, words), "lines")
    levels = doubled(sequences, words)
    tables, copies = later_copies(sequences, levels)
    release(sequences, *levels)
    found = materialize(maximal_runs(copies), "maximal-runs")
    release(*tables)
    keyed = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), *_doc_key())
    # The runs grow with the documents: no broadcast.
    joined = keyed.join(found.hint("merge"), ["d", "t"], "left")

    def lines_of(source: Column) -> Column:
        return F.array_distinct(F.flatten(F.transform(source.runs, lambda r: F.sequence(r.at, r.end - 1))))

    def gone(lines: Column, at: Column) -> Column:
        """The line numbers to cut; at has those of the lines with a word."""

        def chosen(counts: Column) -> Column:
            total = F.aggregate(counts, F.lit(0), lambda a, n: a + n)
            shared = lambda s: F.aggregate(lines_of(s), F.lit(0), lambda a, i: a + F.element_at(counts, i + 1))
            alike = lambda s: 10 * F.least(s.words, total) >= 8 * F.greatest(s.words, total)
            return F.filter("sources", lambda s: ~alike(s) | (shared(s) < version_share * F.greatest(s.words, total)))

        sources = F.col("sources")
        if version_share is not None:
            sources = _bound(F.transform(at, lambda i: _n_words(F.element_at(lines, i + 1))), chosen)
        every = F.array_distinct(F.flatten(F.transform(sources, lines_of)))
        return F.transform(every, lambda i: F.element_at(at, i + 1))

    def rebuilt(lines: Column) -> Column:
        numbers = F.sequence(F.lit(0), F.size(lines) - 1)
        full = F.filter(numbers, lambda i: F.element_at(lines, i + 1).rlike(_WORD))

        def without(cut: Column) -> Column:
            keep = F.transform(F.array_except(numbers, cut), lambda i: F.element_at(lines, i + 1))
            return F.struct(F.when(F.size(cut) > 0, F.array_join(keep, "\n")).alias("text"), F.size(cut).cast("bigint").alias("n"))

        return _bound(_bound(full, lambda at: gone(lines, at)), without)

    made = F.when(F.col("sources").isNotNull(), _bound(F.split("row.text", "\n", -1), rebuilt))
    marked = joined.select("row", "sources", made.alias("made"))
    n_runs = F.aggregate("sources", F.lit(0), lambda a, s: a + F.size(s.runs))
    return marked.select("row", F.coalesce("made.text", "row.text").alias("text"), F.coalesce("made.n", F.lit(0)).alias("n_removed"), F.coalesce(n_runs, F.lit(0)).cast("bigint").alias("n_runs"))


def run_dedup(docs: DataFrame, words: int = WORDS, version_share: float | None = None, least_left: int = 0, length_column: str | None = None) -> DataFrame:
    """The rows and columns of docs, their text without the later copies of all repeated runs of lines that have so many words.

    With version_share, lines stay whose first copies lie in a document of about the same number of words (0.8 at least) and hold
    that share of the longer one's words or more: the two may be versions of one document, which is for a join of whole
    documents to judge. With least_left, a row whose text lost
    lines and has fewer words left than that goes as a whole. length_column names one that follows the length
    of a text that is cut. Rows that lose nothing always stay as they are.
    """
    done = _cut(docs, words, version_share)
    if least_left:
        done = done.where((F.col("n_removed") == 0) | (_n_words(F.col("text")) >= least_left))
    changed = F.col("n_removed") > 0
    values = {"text": F.col("text")}
    if length_column:
        values[length_column] = F.when(changed, F.length("text").cast(docs.schema[length_column].dataType)).otherwise(F.col("row").getField(length_column))
    return done.select(*(values.get(c, F.col("row").getField(c)).alias(c) for c in docs.columns))


def line_dedup_report(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """One row (doc_id, n_lines_removed, kept_chars, kept_md5) for each document."""
    kept = F.coalesce("text", F.lit(""))
    return _cut(docs.select("doc_id", "text"), words, None).select(F.col("row.doc_id").alias("doc_id"), F.col("n_removed").alias("n_lines_removed"), F.length(kept).cast("bigint").alias("kept_chars"), F.md5(kept).alias("kept_md5"))
