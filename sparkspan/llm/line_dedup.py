"""Line deduplication by overlapping windows of three consecutive lines.

Every window is hashed, windows that occur again anywhere are found in one aggregation, and each
occurrence but the first (by document id, then position) marks the lines it covers; the marks of a
document are merged and the marked lines removed. By induction over (document, position) a copy of
every removed line stays: a marked line has an equal line in an earlier window.

What is shuffled: one row of hashes and numbers per window (partially aggregated per task before the
exchange, so a passage that a third of all documents share is one row per task), the windows again
but for the hot ones, and the texts once.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACES, Written, column

SIZE = 3
#: A window is hot if it makes up more than one in HOT of all windows.
HOT = 1000
#: What tells rows apart and orders them.
KEY = ["no", "id", "x", "y"]


def _windows(text: Column, short: bool = False) -> Column:
    """Array of structs (p, a, b): position of the window's first line and its 128-bit hash. With ``short`` a
    text of fewer lines than a window has one window of its own, which ends with the text."""
    keyed = F.transform(F.split(text, "\n"), lambda x: F.struct(F.xxhash64(x).alias("a"), F.xxhash64(x, F.lit(1)).alias("b"), (F.translate(x, SPACES, "") == "").alias("blank")))
    at = lambda k, i, f: F.get(k, i)[f]

    def build(k: Column) -> Column:
        w = F.transform(F.sequence(F.lit(0), F.size(k) - SIZE), lambda i: F.struct(
            i.alias("p"),
            F.xxhash64(*[at(k, i + j, "a") for j in range(SIZE)]).alias("a"),
            F.xxhash64(*[at(k, i + j, "b") for j in reversed(range(SIZE))]).alias("b"),
            (at(k, i, "blank") & at(k, i + 1, "blank") & at(k, i + 2, "blank")).alias("blank"),
        ))
        return F.filter(w, lambda x: ~x["blank"])

    def whole(k: Column) -> Column:
        line = lambda f: [at(k, i, f) for i in range(SIZE - 1)]
        one = F.struct(F.lit(0).alias("p"), F.xxhash64(F.size(k), *line("a")).alias("a"), F.xxhash64(F.size(k), *line("b")).alias("b"), F.forall(k, lambda x: x["blank"]).alias("blank"))
        return F.filter(F.array(one), lambda x: ~x["blank"])

    if short:
        return F.element_at(F.transform(F.array(keyed), lambda k: F.when(F.size(k) >= SIZE, build(k)).otherwise(whole(k))), 1)
    empty = F.array().cast("array<struct<p:int,a:bigint,b:bigint,blank:boolean>>")
    return F.when(F.size(F.split(text, "\n")) >= SIZE, F.element_at(F.transform(F.array(keyed), build), 1)).otherwise(empty)


def _key(id_col: str, text_col: str) -> list[Column]:
    """KEY: null ids last, then the id, then two hashes of the text."""
    ident, text = column(id_col), F.coalesce(column(text_col), F.lit(""))
    return [v.alias(k) for k, v in zip(KEY, (ident.isNull(), F.coalesce(ident.cast("bigint"), F.lit(0)), F.xxhash64(text), F.xxhash64(text, F.lit(1))), strict=True)]


def repeated_starts(df: DataFrame, written: Written, id_col: str = "doc_id", text_col: str = "text", short: bool = False) -> DataFrame:
    """(no, id, x, y, starts): of each row with repeats, the first lines of its later occurrences.

    Windows are made once and written. A window that more than one in ``HOT`` of all windows equal is hot: by
    that definition there are fewer than ``HOT`` of them, so their first places go to every task
    and no task has to hold all their occurrences; every other window is joined by its hash."""
    text, key = F.coalesce(column(text_col), F.lit("")), KEY
    rows = df.select(*_key(id_col, text_col), F.explode(_windows(text, short)).alias("w"))
    spans = written.save(rows.select(*key, "w.p", "w.a", "w.b"))
    total = spans.count()
    first = spans.groupBy("a", "b").agg(F.min(F.struct(*key, "p")).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1")
    first = written.save(first.select("a", "b", "first", (F.col("n") * HOT > total).alias("hot")))
    hot, cold = first.where("hot").drop("hot"), first.where("not hot").drop("hot")
    met = spans.join(F.broadcast(hot), ["a", "b"], "left")
    later = met.where("first is not null").unionByName(met.where("first is null").drop("first").join(cold, ["a", "b"]))
    return later.where(F.struct(*key, "p") != F.col("first")).groupBy(*key).agg(F.collect_set("p").alias("starts"))


def dedup_lines(df: DataFrame, written: Written, id_col: str = "doc_id", text_col: str = "text", short: bool = False) -> DataFrame:
    """One row per document: its id, n_lines, n_removed (long) and the text that stays.

    A null or empty text has one empty line and loses nothing; fewer than three lines lose nothing unless
    ``short``, by which all lines of such a text go if an earlier text is the same; the SQL of the query
    is without it. Shorter passages within a text are not seen. Windows of blank lines only do not count.
    Rows are told apart by id and text: rows of one id with several texts come in the order of a hash of
    the text, rows with a null id after all others; rows that repeat id and text both have the same
    marks (one is no repeat of the other, which exact deduplication is for). An empty table gives an empty
    result. Other columns are not read.
    """
    docs = df.select(column(id_col).alias("own"), *_key(id_col, text_col), F.coalesce(column(text_col), F.lit("")).alias("t"))
    joined = docs.join(repeated_starts(df, written, id_col, text_col, short), KEY, "left")
    lines = F.split(F.col("t"), "\n")
    n = F.size(lines)
    gone = F.array_distinct(F.flatten(F.transform("starts", lambda p: F.array(*[p + j for j in range(SIZE)]))))
    if short:
        gone = F.filter(gone, lambda i: i < n)
    kept = F.array_except(F.sequence(F.lit(0), n - 1), gone)
    text = F.element_at(F.transform(F.array(lines), lambda all_: F.array_join(F.transform(kept, lambda i: F.get(all_, i)), "\n")), 1)
    return joined.select(
        F.col("own").alias(id_col),
        n.cast("bigint").alias("n_lines"),
        F.when(F.col("starts").isNull(), 0).otherwise(F.size(gone)).cast("bigint").alias("n_removed"),
        F.when(F.col("starts").isNull(), F.col("t")).otherwise(text).alias("text"),
    )


SQL = """
with docs as (select doc_id, coalesce(text, '') as t from documents),
lines as (select doc_id, unnest(string_split(t, chr(10))) as line, unnest(range(len(string_split(t, chr(10))))) as p from docs),
win as (select doc_id, p, line, lead(line, 1) over o as l1, lead(line, 2) over o as l2 from lines window o as (partition by doc_id order by p)),
real as (select * from win where l2 is not null and regexp_matches(line || l1 || l2, '[^\\x20\\x09-\\x0D]')),
ranked as (select doc_id, p, row_number() over (partition by line, l1, l2 order by doc_id, p) as r from real),
gone as (select distinct doc_id, p + j as p from ranked, (select unnest([0, 1, 2]) as j) where r > 1)
select l.doc_id, cast(count(*) as bigint) as n_lines, cast(count(g.p) as bigint) as n_removed,
 coalesce(string_agg(case when g.p is null then line end, chr(10) order by l.p), '') as text
from lines l left join gone g on g.doc_id = l.doc_id and g.p = l.p group by l.doc_id
"""
