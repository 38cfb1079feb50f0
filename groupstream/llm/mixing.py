"""Mixing sources to target weights by Pareto order sampling (DataFrame operators only).

A source's target divided by its size is the expected number of copies of each of its documents. The whole part of it is
certain: every document is taken that often. The fraction is an inclusion probability. Documents are ranked by random
odds over inclusion odds, q = (u / (1 - u)) / (p / (1 - p)), with u a hash of the document's id and text, and the first ones
that together hold the missing words are taken once more. Then, on down the same order, every document that still fits into
what is left is taken too, in rounds, until none fits. Rows of one source that are equal in q and size are a class of
interchangeable rows; a class that does not fit as a whole gives as many of its rows as fit.

No source is ever sorted as a whole. q is cut into BINS ranges; sums of words per source and range find the range in
which the target falls, and only the classes of that range are ordered. A hot source or a row that occurs very often is
thus pre-aggregated, and its share of the work grows with its rows in map tasks alone. The table of sources, one row each,
is put in order by one task.

Cases: null and empty texts have size 0 and are never short of words, hence they get the certain copies only or rank like
others with size 0; a null source is a source of its own, last in order; rows equal in id and text rank alike and are
dealt one by one, whatever their other columns; an empty table gives an empty result; other columns are kept, and columns
named like the results are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, md5_bits, n_words

BINS = 4096
WEIGHTS = (5, 2, 1)
MOST = 3


def source_key(source: Column) -> Column:
    """A string that orders like the source by code point, with null last."""
    return F.when(source.isNull(), F.lit("b")).otherwise(F.concat(F.lit("a"), source))


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST) -> DataFrame:
    """(key, size) per row -> (key, source_size, weight, target), one row per source.

    A target is at most `most` times the source's size. With sources ordered by that bound over their weight, the sources
    that stop at the bound are a prefix, so the shared level has a closed form: that of the first prefix at which the level
    of the rest does not exceed the next bound. Longer prefixes only lower it, so it is the largest such level.
    """
    per = sizes.groupBy("key").agg(F.sum("size").alias("source_size"))
    place = F.row_number().over(Window.orderBy("key")) - 1
    cycle = F.array(*[F.lit(w) for w in weights])
    per = per.withColumn("weight", F.get(cycle, F.pmod(place, F.lit(len(weights))))).withColumn("weight", F.col("weight").cast("long"))
    bound = (F.lit(most) * F.col("source_size")).cast("double") / F.col("weight")
    order = Window.orderBy("bound", "key")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    per = per.withColumn("bound", bound)
    per = per.withColumns(
        {
            "held": F.lit(most) * F.coalesce(F.sum("source_size").over(before), F.lit(0)),
            "passed": F.coalesce(F.sum("weight").over(before), F.lit(0)),
            "all_size": F.sum("source_size").over(everything),
            "all_weight": F.sum("weight").over(everything),
        }
    )
    level = (F.col("all_size") - F.col("held")).cast("double") / (F.col("all_weight") - F.col("passed"))
    per = per.withColumn("own", F.when(level <= F.col("bound"), level))
    per = per.withColumn("level", F.max("own").over(everything))
    target = F.least(F.col("weight") * F.col("level"), (F.lit(most) * F.col("source_size")).cast("double"))
    return per.select("key", "source_size", "weight", F.coalesce(target, F.lit(0.0)).alias("target"))


def _rank(u: Column, p: Column) -> Column:
    return (u / (1.0 - u)) / F.nullif(p / (1.0 - p), F.lit(0.0))


def _bin(q: Column) -> Column:
    return F.least(F.floor(q / (1.0 + q) * BINS), F.lit(BINS - 1)).cast("int")


def _prefix(rows: DataFrame) -> DataFrame:
    """rows (key, room, size, q) -> (key, got, upto, upto_size, part): the longest prefix of each key's order within its
    room. It takes all rows up to (upto, upto_size) and, where `part` is set, of the class (q, size) in it `many`.

    Only the range where the room ends is looked at row by row. What is known of the ranges before it goes along with its
    rows, so tables of keys are not joined with each other.
    """
    rows = rows.withColumn("bin", _bin(F.col("q")))
    bins = rows.groupBy("key", "room", "bin").agg(F.sum("size").alias("words"), F.max(F.struct("q", "size")).alias("last"))
    up = Window.partitionBy("key", "room").orderBy("bin")
    bins = bins.withColumns(
        {
            "sum": F.sum("words").over(up.rowsBetween(Window.unboundedPreceding, Window.currentRow)),
            "whole": F.lag("last").over(up),
        }
    )
    here = F.struct("bin", (F.col("sum") - F.col("words")).alias("start"), "whole")
    fits = F.col("sum") <= F.col("room")
    ends = bins.groupBy("key", "room").agg(F.min(F.when(~fits, here)).alias("at"), F.max("last").alias("last"), F.max("sum").alias("got"))
    all_of_it = ends.where("at is null").select("key", "last", F.lit(None).cast("struct<q:double,size:bigint,many:bigint>").alias("part"), "got")
    classes = rows.join(ends.where("at is not null").select("key", "at.*"), ["key", "bin"]).groupBy("key", "room", "q", "size").agg(F.count(F.lit(1)).alias("n"), F.first("start").alias("start"), F.first("whole").alias("whole"))
    inside = Window.partitionBy("key", "room").orderBy("q", "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    classes = classes.withColumn("sum", F.col("start") + F.sum(F.col("n") * F.col("size")).over(inside))
    before = F.col("sum") - F.col("n") * F.col("size")
    many = F.floor((F.col("room") - before) / F.nullif("size", F.lit(0)))
    edge = ~fits & (before <= F.col("room")) & (many > 0)  # one class of a key at most
    found = classes.groupBy("key", "room").agg(
        F.max(F.when(fits, F.struct("q", "size"))).alias("last"),
        F.first("whole").alias("whole"),
        F.max(F.when(edge, F.struct("q", "size", many.alias("many")))).alias("part"),
        F.max(F.when(edge, before + many * F.col("size")).when(fits, F.col("sum")).otherwise(F.col("start"))).alias("got"),
    )
    last = F.coalesce("last", "whole", F.struct(F.lit(-1.0).alias("q"), F.lit(0).cast("long").alias("size")))
    found = found.select("key", last.alias("last"), "part", "got").unionByName(all_of_it)
    last = F.col("last")
    return found.select("key", F.col("got").cast("long").alias("got"), last["q"].alias("upto"), last["size"].alias("upto_size"), "part")


_BOUND = "room:bigint,upto:double,upto_size:bigint,part:struct<q:double,size:bigint,many:bigint>"


def plan(rows: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST) -> DataFrame:
    """(key, size, u) per document -> one row per source: target, certain copies, probability and the bounds of each round.

    bounds is an array of (room, upto, upto_size, part): a document that no earlier round took, of at most `room` words and
    with (q, size) up to (upto, upto_size), is taken in that round, and so are `part.many` of the class (part.q, part.size).
    What did not fit has more words than are left, so a round ends with fewer candidates for the next, and all end.
    """
    goals = source_targets(rows, weights, most)
    ratio = F.coalesce(F.try_divide(F.col("target"), F.col("source_size")), F.lit(0.0))
    goals = goals.withColumn("certain", F.least(F.floor(ratio), F.lit(most)).cast("long"))
    goals = goals.withColumn("p", F.when(F.col("certain") >= most, 0.0).otherwise(F.greatest(ratio - F.col("certain"), F.lit(0.0))))
    goals = goals.withColumn("room", F.when(F.col("p") > 0, F.round(F.col("target") - F.col("certain") * F.col("source_size")).cast("long")).otherwise(F.lit(0).cast("long")))
    goals = cut(goals.withColumn("bounds", F.expr(f"cast(array() as array<struct<{_BOUND}>>)")), "mix-goals")
    first = True
    while True:
        left = rows.join(goals.where("p > 0 AND room > 0"), "key").withColumn("q", _rank(F.col("u"), F.col("p")))
        left = left.where((F.col("size") <= F.col("room")) & F.col("q").isNotNull() & ~_taken("bounds", "size", "q")).select("key", "room", "size", "q")
        left = left if first else cut(left, "mix-left")  # less than the room of the round before in each row
        if left.where("size > 0").isEmpty():
            return goals.drop("room")
        found = _prefix(left)
        bound = F.struct("room", "upto", "upto_size", "part").cast(f"struct<{_BOUND}>")
        goals = cut(
            goals.join(found, "key", "left")
            .withColumn("bounds", F.when(F.col("upto").isNull(), F.col("bounds")).otherwise(F.concat("bounds", F.array(bound))))
            .withColumn("room", F.col("room") - F.coalesce("got", F.lit(0)))
            .drop("got", "upto", "upto_size", "part"),
            "mix-round",
        )
        first = False


def _taken(bounds: str, size: str, q: str, part: bool = True) -> Column:
    """Whether some round took the row; with `part`, rows of classes that a round took in part count as well."""
    size, q = F.col(size), F.col(q)

    def by(b: Column) -> Column:
        whole = (size <= b["room"]) & ((q < b["upto"]) | ((q == b["upto"]) & (size <= b["upto_size"])))
        return whole | (b["part"].isNotNull() & (q == b["part"]["q"]) & (size == b["part"]["size"])) if part else whole

    return F.exists(bounds, by)


def _numbered(rows: DataFrame) -> DataFrame:
    """rows of classes taken in part, with __n, their number inside the class, from 1. They are written out once, so the
    parts of the table that they stand in stay; each part numbers its own, and sums over parts say where it starts."""
    held = cut(rows.withColumn("__p", F.spark_partition_id()), "mix-parts")
    cls = ["__key", "__q", "__size"]
    per = held.groupBy(*cls, "__p").agg(F.count(F.lit(1)).alias("__m"))
    before = Window.partitionBy(*cls).orderBy("__p").rowsBetween(Window.unboundedPreceding, -1)
    per = per.select(*[F.col(c).alias(f"{c}2") for c in [*cls, "__p"]], F.coalesce(F.sum("__m").over(before), F.lit(0)).alias("__from"))
    own = F.row_number().over(Window.partitionBy(*cls, "__p").orderBy(F.xxhash64(*held.columns)))
    numbered = held.withColumn("__own", own)
    same = [F.col(c) == F.col(f"{c}2") for c in [*cls, "__p"]]
    return numbered.join(per, same).withColumn("__n", F.col("__own") + F.col("__from")).select(*rows.columns, "__n")


def mix(docs: DataFrame, seed: str = "mix", id_column: str = "doc_id", text: str = "text", source: str = "source", **kw) -> DataFrame:
    """docs with size, source_size, target, copies and taken (copies * size) for each row."""
    made = ["size", "source_size", "target", "copies", "taken"]
    keep = [c for c in docs.columns if c not in made]
    u = md5_bits(F.concat_ws("|", F.lit(seed), F.col(id_column).cast("string"), F.col(text)), 13) / F.lit(float(1 << 52))
    rows = docs.select(*keep, source_key(F.col(source)).alias("__key"), n_words(F.col(text)).alias("__size"), u.alias("__u"))
    slim = cut(rows.select(F.col("__key").alias("key"), F.col("__size").alias("size"), F.col("__u").alias("u")), "mix-sizes")
    goals = plan(slim, **kw)
    by_source = goals.select(F.col("key").alias("__key"), "source_size", "target", F.col("certain").alias("__certain"), F.col("p").alias("__p"), F.col("bounds").alias("__bounds"))
    ranked = rows.join(by_source, "__key").withColumn("__q", _rank(F.col("__u"), F.col("__p")))
    whole = F.coalesce(_taken("__bounds", "__size", "__q", False), F.lit(False))
    once_more = whole
    if not goals.where(F.exists("bounds", lambda b: b["part"].isNotNull())).isEmpty():
        own = F.filter("__bounds", lambda b: b["part"].isNotNull() & (F.col("__q") == b["part"]["q"]) & (F.col("__size") == b["part"]["size"]))
        ranked = ranked.withColumn("__part", F.when(whole, F.lit(None)).otherwise(F.get(F.coalesce(own, F.array()), F.lit(0))["part"]["many"]))
        others = ranked.where("__part is null").withColumn("__n", F.lit(None).cast("long"))
        ranked = others.unionByName(_numbered(ranked.where("__part is not null")))
        once_more = whole | F.coalesce(F.col("__n") <= F.col("__part"), F.lit(False))
    out = ranked.withColumn("copies", F.col("__certain") + once_more.cast("long"))
    return out.select(*keep, F.col("__size").alias("size"), "source_size", "target", "copies", (F.col("copies") * F.col("__size")).alias("taken"))


def draw(docs: DataFrame, **kw) -> DataFrame:
    """The mix itself: each document as often as it was taken."""
    return mix(docs, **kw).where("copies > 0").withColumn("__copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select(*docs.columns)


def query(spark, sf_dir):
    from .common import table

    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    return mix(docs).select("doc_id", "size", "source_size", "target", "taken", "copies")


SQL = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, CASE WHEN source IS NULL THEN 'b' ELSE 'a' || source END AS k,
         len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
         ('0x' || substr(md5(concat_ws('|', 'mix', doc_id::VARCHAR, text)), 1, 13))::BIGINT::DOUBLE / 4503599627370496.0::DOUBLE AS u
  FROM documents),
s0 AS (SELECT k, sum(size)::BIGINT AS s FROM d GROUP BY k),
s1 AS (SELECT *, [5, 2, 1][((row_number() OVER (ORDER BY k) - 1) % 3) + 1]::BIGINT AS w FROM s0),
s2 AS (SELECT *, (3 * s)::DOUBLE / w::DOUBLE AS bound FROM s1),
s3 AS (SELECT *, 3 * coalesce(sum(s) OVER o, 0)::BIGINT AS held, coalesce(sum(w) OVER o, 0)::BIGINT AS passed,
              (sum(s) OVER ())::BIGINT AS ts, (sum(w) OVER ())::BIGINT AS tw
       FROM s2 WINDOW o AS (ORDER BY bound, k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
s4 AS (SELECT *, (ts - held)::DOUBLE / (tw - passed)::DOUBLE AS lv FROM s3),
s5 AS (SELECT *, max(CASE WHEN lv <= bound THEN lv END) OVER () AS level FROM s4),
s6 AS (SELECT k, s, coalesce(least(w::DOUBLE * level, (3 * s)::DOUBLE), 0.0::DOUBLE) AS target FROM s5),
s7 AS (SELECT *, CASE WHEN s > 0 THEN target / s::DOUBLE ELSE 0.0::DOUBLE END AS r FROM s6),
s8 AS (SELECT *, least(floor(r), 3)::BIGINT AS c FROM s7),
s9 AS (SELECT *, CASE WHEN c >= 3 THEN 0.0::DOUBLE ELSE greatest(r - c::DOUBLE, 0.0::DOUBLE) END AS p FROM s8),
g AS (SELECT *, CASE WHEN p > 0 THEN round(target - (c * s)::DOUBLE)::BIGINT ELSE 0 END AS room FROM s9),
e0 AS (SELECT d.*, g.s, g.target, g.c, g.room, row_number() OVER () AS i,
              CASE WHEN g.p > 0 THEN (u / (1.0::DOUBLE - u)) / (g.p / (1.0::DOUBLE - g.p)) END AS q
       FROM d JOIN g USING (k)),
rounds AS (
  SELECT 0 AS n, i, k, size, q, room, false AS t FROM e0
  UNION ALL
  SELECT n + 1, i, k, size, q, room - coalesce(sum(CASE WHEN now THEN size END) OVER (PARTITION BY k), 0)::BIGINT, t OR now
  FROM (SELECT *, bool_or(may AND size > 0) OVER () AS more, coalesce(may, false) AND
               sum(CASE WHEN may THEN size ELSE 0 END) OVER (PARTITION BY k ORDER BY q, size, i ROWS UNBOUNDED PRECEDING) <= room AS now
        FROM (SELECT *, q IS NOT NULL AND NOT t AND size <= room AND room > 0 AS may FROM rounds))
  WHERE more),
done AS (SELECT i, t FROM rounds WHERE n = (SELECT max(n) FROM rounds))
SELECT doc_id, size, s AS source_size, target, (c + t::BIGINT) * size AS taken, c + t::BIGINT AS copies
FROM e0 JOIN done USING (i)
"""
