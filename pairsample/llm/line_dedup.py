"""Corpus-wide line deduplication by a deletion-neighbourhood join, with DataFrame functions only.

A line is trimmed and cut into words at its blanks. Two lines are the same if they are equal, and near if one word put in, left
out or replaced turns one into the other and this is at most a share ``1 - min_similarity`` of the longer one. A line
goes if an earlier line (smaller id, then smaller position) is the same or near; blank lines always stay.

Every line with one word left out gives a variant; equal variants meet. Emitting them for all lines would multiply
the text, so lines first meet on halves: one edit leaves either the first or the last ``h`` words alone for any
``h`` up to half the shorter length, so a line that shares no such half with another line has no near line.
Nothing pairs up the members of a group: all that a decision needs is the earliest member, an aggregate.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pairsample.llm.common import Scratch

NO_ID = 2**63 - 1
BLANKS = " \t\r\x0b\x0c"


#: The largest table that is broadcast, in rows of a few dozen bytes; counted first, and joined by shuffle beyond it.
BROADCAST_ROWS = 1_000_000


def _bounded(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else df


def _half(n: Column) -> Column:
    """The largest power of two up to half of n, so that most neighbouring lengths share it."""
    return F.pow(F.lit(2.0), F.floor(F.log2(n / 2))).cast("int")


def _lines(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    source = docs.select(
        F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("d"),
        F.xxhash64(F.col(text_col).cast("string")).alias("th"),
        F.posexplode(F.split(F.col(text_col).cast("string"), "\n")).alias("pos", "raw"),
    )
    line = source.select("d", "th", "pos", F.btrim("raw", F.lit(BLANKS)).alias("line")).where("line <> ''")
    return line.select(F.xxhash64("line").alias("k1"), F.xxhash64(F.lit("second"), "line").alias("k2"), "d", "pos", "th", "line")


def _halves(line: Column, min_similarity: float) -> Column:
    """Hashes of the first and last halves under which a line can meet its near lines; none for a line too short to have any."""
    w = F.split(line, " ")
    n = F.size(w)

    def ends(h: Column) -> list[Column]:
        return [F.xxhash64(F.lit("first"), h, F.slice(w, 1, h)), F.xxhash64(F.lit("last"), h, F.slice(w, -h, h))]

    own, less = _half(n), _half(F.greatest(n - 1, F.lit(2)))
    both = F.when(own == less, F.array(*ends(own))).otherwise(F.array(*ends(own), *ends(less)))
    return F.when(((n + 1) * (1 - min_similarity) >= 1 - 1e-9) & (n >= 2), both).otherwise(F.array().cast("array<long>"))


def near_lines(scratch: Scratch, lines: DataFrame, distinct: DataFrame, min_similarity: float = 0.8) -> DataFrame:
    """The distinct lines (k1, k2, d, pos, halves) that have an earlier near line: (k1, k2)."""
    halves = distinct.select("k1", F.explode("halves").alias("half"))
    shared = halves.groupBy("half").agg(F.min("k1").alias("lo"), F.max("k1").alias("hi")).where("lo <> hi").select("half")
    meets = scratch.write(distinct.select("k1", "k2", "d", "pos", F.explode("halves").alias("half")).join(_bounded(scratch.write(shared)), "half").select("k1", "k2", "d", "pos").distinct())
    able = lines.select("k1", "k2", "d", "pos", "line").join(_bounded(meets), ["k1", "k2", "d", "pos"]).dropDuplicates(["k1", "k2"])
    able = scratch.write(able.withColumn("w", F.split("line", " ")).drop("line").withColumn("n", F.size("w")))

    words = able.select("k1", "k2", "d", "pos", "n", F.posexplode("w").alias("i", "word"))
    marks = words.select("k1", "k2", "d", "pos", "n", "i", F.xxhash64("word", "i").alias("here"), F.xxhash64("word", F.col("i") - 1).alias("moved"))
    whole = Window.partitionBy("k1", "k2")
    upto = whole.orderBy("i").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    cut = scratch.write(marks.select(
        "k1", "k2", "d", "pos", "n", "i",
        F.expr("bit_xor(here)").over(whole).alias("own"),
        F.expr("bit_xor(here)").over(upto).bitwiseXOR(F.col("here")).bitwiseXOR(F.expr("bit_xor(moved)").over(whole)).bitwiseXOR(F.expr("bit_xor(moved)").over(upto)).alias("left_out"),
    ))
    at = F.struct("d", "pos", "k1", "k2").alias("at")
    variants = cut.select(at, F.col("left_out").alias("v"), (F.col("n") - 1).alias("m"), "i").unionByName(cut.where("i = 0").select(at, F.col("own").alias("v"), F.col("n").alias("m"), F.lit(-1).alias("i")))
    # the longer of two lines that meet here has m + 1 words; where one edit is too much for it, they are no candidates
    variants = variants.where((F.col("m") + 1) * (1 - min_similarity) >= 1 - 1e-9)
    equal = variants.groupBy("v", "m").agg(F.min("at.k1").alias("lo"), F.max("at.k1").alias("hi")).where("lo <> hi").select("v", "m")
    met = scratch.write(variants.join(_bounded(scratch.write(equal)), ["v", "m"]))
    # the same words left at the same place: one word replaced. The whole of a line (i = -1) and a variant: one word more
    first = met.groupBy("v", "m", "i").agg(F.min("at").alias("rep"))
    whole_first, part_first = first.where("i = -1").select("v", "m", "rep"), first.where("i >= 0").groupBy("v", "m").agg(F.min("rep").alias("rep"))
    replaced = met.where("i >= 0").join(first, ["v", "m", "i"]).select("at", "rep")
    longer = met.where("i >= 0").join(whole_first, ["v", "m"]).select("at", "rep")
    shorter = met.where("i = -1").join(part_first, ["v", "m"]).select("at", "rep")
    found = replaced.unionByName(longer).unionByName(shorter).where("rep < at").groupBy("at").agg(F.min("rep").alias("rep"))

    # hashes only proposed; the words of both lines decide
    mine = found.select("at.k1", "at.k2", "rep").join(able.select("k1", "k2", "w", "n"), ["k1", "k2"])
    theirs = able.select(F.col("k1").alias("r1"), F.col("k2").alias("r2"), F.col("w").alias("x"), F.col("n").alias("m"))
    both = mine.join(theirs, (F.col("rep.k1") == F.col("r1")) & (F.col("rep.k2") == F.col("r2")))

    def common(a: Column, b: Column) -> Column:
        short = F.least(F.size(a), F.size(b))
        first = F.array_position(F.zip_with(a, b, lambda p, q: F.coalesce(p != q, F.lit(True))), True)
        return F.least(short, F.when(first > 0, first.cast("int") - 1).otherwise(short))

    longest = F.greatest("n", "m")
    one_edit = (F.abs(F.col("n") - F.col("m")) <= 1) & (common(F.col("w"), F.col("x")) + common(F.reverse("w"), F.reverse("x")) >= longest - 1)
    return both.where(one_edit & (longest * (1 - min_similarity) >= 1 - 1e-9)).select("k1", "k2")


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_similarity: float = 0.8) -> DataFrame:
    """Each row of ``docs`` with its text freed of lines that an earlier row or position holds, and two counts.

    Returns all columns of ``docs`` with ``text_col`` replaced, then n_lines and n_dropped (columns of these names in
    ``docs`` are replaced). A null text stays null with 0 lines. Rows without an id come last in the order and are told
    apart by their text. Rows that repeat an id and a text are one origin and keep the same lines. Empty tables give empty ones.
    """
    scratch = Scratch(docs.sparkSession, "lines")
    lines = _lines(docs, id_col, text_col)
    distinct = scratch.write(
        lines.select("k1", "k2", "d", "pos", _halves(F.col("line"), min_similarity).alias("halves"))
        .groupBy("k1", "k2")
        .agg(F.min(F.struct("d", "pos")).alias("at"), F.max(F.struct("d", "pos")).alias("last"), F.first("halves").alias("halves"))
        .select("k1", "k2", "at.d", "at.pos", "last", "halves")
    )
    near = near_lines(scratch, lines, distinct, min_similarity).withColumn("near", F.lit(True))
    acting = scratch.write(
        distinct.select("k1", "k2", F.col("d").alias("d0"), F.col("pos").alias("pos0"), "last")
        .join(near, ["k1", "k2"], "left")
        .where(F.col("near") | (F.struct(F.col("d0").alias("d"), F.col("pos0").alias("pos")) < F.col("last")))
        .select("k1", "k2", "d0", "pos0", F.coalesce("near", F.lit(False)).alias("near"))
    )
    gone = (
        lines.select("k1", "k2", "d", "pos", "th")
        .join(acting, ["k1", "k2"])
        .where("near or d <> d0 or pos <> pos0")
        .groupBy("d", "th")
        .agg(F.collect_set("pos").alias("gone"))
    )
    others = [c for c in docs.columns if c not in ("n_lines", "n_dropped")]
    keyed = docs.select(
        F.struct(*[F.col(f"`{c}`") for c in others]).alias("row"),
        F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("d"),
        F.xxhash64(F.col(text_col).cast("string")).alias("th"),
    )
    cut = keyed.join(gone, ["d", "th"], "left").withColumn("lines", F.split(F.col("row").getField(text_col).cast("string"), "\n"))
    kept = F.array_except(F.sequence(F.lit(0), F.size("lines") - 1), F.col("gone"))
    text = F.when(F.col("gone").isNull(), F.col("row").getField(text_col)).otherwise(F.array_join(F.transform(kept, lambda i: F.col("lines")[i]), "\n"))
    return cut.select(
        *[text.alias(c) if c == text_col else F.col("row").getField(c).alias(c) for c in others],
        F.when(F.col("lines").isNull(), 0).otherwise(F.size("lines")).cast("long").alias("n_lines"),
        F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("n_dropped"),
    )


ORACLE = r"""
WITH src AS (SELECT doc_id, string_split(text, chr(10)) AS ls FROM documents WHERE text IS NOT NULL),
raw AS (SELECT doc_id, unnest(ls) AS line, unnest(range(0, len(ls))) AS pos FROM src),
l AS (SELECT doc_id, pos, string_split(trim(line, ' ' || chr(9) || chr(13) || chr(11) || chr(12)), ' ') AS w FROM raw
      WHERE trim(line, ' ' || chr(9) || chr(13) || chr(11) || chr(12)) <> ''),
o AS (SELECT *, row_number() OVER (PARTITION BY w ORDER BY doc_id, pos) AS k FROM l),
d AS (SELECT w, len(w) AS n, doc_id * 1000000 + pos AS ord FROM o WHERE k = 1),
h AS (SELECT w, n, ord, c, 'first' AS side, w[1:c // 2] AS half FROM d, LATERAL (SELECT unnest([n, n - 1]) AS c) WHERE n >= 4
      UNION ALL SELECT w, n, ord, c, 'last', w[n - c // 2 + 1:n] FROM d, LATERAL (SELECT unnest([n, n - 1]) AS c) WHERE n >= 4),
p AS (SELECT DISTINCT b.w AS w, b.n AS n, a.w AS x, a.n AS m FROM h a JOIN h b ON a.c = b.c AND a.side = b.side AND a.half = b.half
      WHERE a.ord < b.ord AND least(a.n, b.n) = a.c AND greatest(a.n, b.n) >= 5 AND abs(a.n - b.n) <= 1),
s AS (SELECT w, n, m,
        coalesce(list_position(list_transform(range(1, least(n, m) + 1), lambda i: w[i] <> x[i]), true), 0) AS f,
        coalesce(list_position(list_transform(range(1, least(n, m) + 1), lambda i: w[n - i + 1] <> x[m - i + 1]), true), 0) AS b FROM p),
near AS (SELECT DISTINCT w FROM s
         WHERE (CASE WHEN f > 0 THEN f - 1 ELSE least(n, m) END) + (CASE WHEN b > 0 THEN b - 1 ELSE least(n, m) END) >= greatest(n, m) - 1),
gone AS (SELECT doc_id, pos FROM o WHERE k > 1 OR w IN (SELECT w FROM near)),
kept AS (SELECT r.doc_id, string_agg(r.line, chr(10) ORDER BY r.pos) AS text, count(*) AS left_over FROM raw r
         ANTI JOIN gone g ON r.doc_id = g.doc_id AND r.pos = g.pos GROUP BY r.doc_id)
SELECT t.doc_id, coalesce(len(s.ls), 0)::BIGINT AS n_lines, (coalesce(len(s.ls), 0) - coalesce(k.left_over, 0))::BIGINT AS n_dropped,
       CASE WHEN t.text IS NOT NULL THEN md5(coalesce(k.text, '')) END AS text_md5
FROM documents t LEFT JOIN src s ON t.doc_id = s.doc_id LEFT JOIN kept k ON t.doc_id = k.doc_id
"""
