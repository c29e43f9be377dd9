"""Mixing sources to target weights by systematic sampling over prefix sums."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tricount.llm.common import WORD, Stages, unused

#: Rows of a part of a size class of a source, which are ranked together, and parts that are summed up together.
PART_ROWS, PARTS = 128, 1024
#: A document with at least this share (one in so many) of its source's words is placed by itself; a source has no more of these.
LARGE = 512
#: No document is taken more often than this.
MOST = 3


def _words() -> Column:
    return F.coalesce(F.regexp_count(F.coalesce("text", F.lit("")), F.lit(WORD)), F.lit(0)).cast("long")


def _targets(sources: DataFrame) -> DataFrame:
    """(key, none, source_size, target): one row per source, so windows over all sources see only that many rows."""
    by_name = W.orderBy("none", "key")
    weighed = sources.withColumn("w", (1 + (F.row_number().over(by_name) - 1) % 3).cast("long"))
    before = W.orderBy((F.lit(MOST) * F.col("source_size")).cast("double") / F.col("w"), "none", "key").rowsBetween(W.unboundedPreceding, -1)
    all_rows = W.partitionBy(F.lit(1)).rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    level = (F.sum("source_size").over(all_rows) - F.coalesce(F.sum(MOST * F.col("source_size")).over(before), F.lit(0))).cast("double") / (
        F.sum("w").over(all_rows) - F.coalesce(F.sum("w").over(before), F.lit(0))
    ).cast("double")
    # Sources fill up in the order of limit / weight; the level rises while they do and falls from then on.
    filled = weighed.withColumn("level", level).withColumn("level", F.max("level").over(all_rows))
    return filled.select("key", "none", "source_size", F.least((MOST * F.col("source_size")).cast("double"), F.col("level") * F.col("w")).alias("target"))


def _rate(asked: Column, there: Column) -> Column:
    """Expected copies of each word, so that `there` words give `asked`."""
    return F.when(there > 0, F.least(F.greatest(asked / there.cast("double"), F.lit(0.0)), F.lit(float(MOST)))).otherwise(F.lit(0.0))


def _offset() -> Column:
    return F.conv(F.substring(F.md5(F.concat("key", F.col("none").cast("string"))), 1, 4), 16, 10).cast("double") / F.lit(65536.0)


def _placed(targets: DataFrame, large: DataFrame) -> DataFrame:
    """(key, none, source_size, target, sums, rest): `sums` the running expected copies of the source's large documents, biggest first, and `rest` the rate of all others.

    Every document expects what is still asked for, over the words that are still there: so what whole copies gave too much or too little goes into all that follow.
    """
    sizes = large.groupBy("key", "none").agg(F.sort_array(F.collect_list("size"), asc=False).alias("sizes"))
    start = F.struct(
        F.lit(0.0).alias("sum"), F.lit(0).cast("long").alias("taken"), F.lit(0).cast("long").alias("seen"), F.array().cast("array<double>").alias("sums"),
    )

    def step(s: Column, size: Column) -> Column:
        upto = s["sum"] + _rate(F.col("target") - s["taken"].cast("double"), F.col("source_size") - s["seen"])
        copies = (F.floor(upto + F.col("offset")) - F.floor(s["sum"] + F.col("offset"))).cast("long")
        return F.struct(upto.alias("sum"), (s["taken"] + copies * size).alias("taken"), (s["seen"] + size).alias("seen"), F.concat(s["sums"], F.array(upto)).alias("sums"))

    joined = targets.join(sizes, ["key", "none"], "left").withColumn("offset", _offset())
    run = joined.withColumn("run", F.aggregate(F.coalesce("sizes", F.array().cast("array<bigint>")), start, step))
    rest = _rate(F.col("target") - F.col("run.taken").cast("double"), F.col("source_size") - F.col("run.seen"))
    return run.select("key", "none", "source_size", "target", "offset", F.col("run.sums").alias("sums"), F.col("run.sum").alias("upto"), rest.alias("rest"))


def mix(docs: DataFrame) -> DataFrame:
    """Every document with how often the mix takes it: doc_id, source, size, source_size, target, copies, taken.

    Size is the number of words. Sources in code point order (null last) weigh 1, 2, 3, repeating, and share the total of all sizes
    by weight; none is asked for more than three times its own size, and what is over goes to the others by weight. Expected copies are summed up over the
    source from its largest document down, and with one offset for the source (from the hash of its name) a document is emitted once for each integer
    its stretch of the sum crosses. All documents expect target / source_size copies, but for what whole copies of the larger ones gave too much or too little:
    documents with at least a LARGE-th of the source's words (no more than LARGE of them) are summed one after another, each expecting what is still asked for over
    what is still there, and all others share one rate. So a source misses its target by about the size of its smallest documents where these can make up for the rest.

    The sum over the small ones has three levels: ranks within a part of a size class of a source, of some PART_ROWS rows; sums over PARTS parts; and sums of these over a source,
    a table of a row for some hundred thousand documents, or for each size class. Sizes are written once to the shared folder, so texts are read once. The same rows always give the same mix. Null texts and texts without words
    have size 0 and are drawn like others. Null ids go first within their size. A source of size 0 has target 0. An empty table gives no rows.
    """
    stages = Stages(docs.sparkSession, "mix")
    words = docs.select("doc_id", "source", _words().alias("size"))
    rows = stages.write(
        words.withColumns(
            {
                "key": F.coalesce("source", F.lit("")),
                "none": F.col("source").isNull().cast("int"),
                "class": F.expr("CASE WHEN size < 16 THEN size ELSE length(bin(size)) * 8 + (shiftright(size, length(bin(size)) - 4) & 7) END"),
                "draw": F.conv(F.substring(F.md5(F.concat_ws(":", "doc_id", "size")), 1, 8), 16, 10).cast("long"),
            }
        )
    )
    classes = rows.groupBy("key", "none", "class").agg(F.count(F.lit(1)).alias("held"), F.sum("size").alias("words"))
    targets = stages.write(_targets(classes.groupBy("key", "none").agg(F.sum("words").alias("source_size"))))
    sized = rows.join(targets.select("key", "none", "source_size"), ["key", "none"])
    is_large = (F.col("size") > 0) & (F.col("size") * LARGE >= F.col("source_size"))
    large = sized.where(is_large)
    placed = stages.write(_placed(targets, large))
    crossed = lambda upto: F.floor(upto + F.col("offset"))
    columns = ["doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken")]
    by_size = W.partitionBy("key", "none").orderBy(F.desc("size"), F.col("doc_id").asc_nulls_first())
    one_by_one = large.drop("source_size").withColumn("at", F.row_number().over(by_size)).join(placed, ["key", "none"])
    before = F.when(F.col("at") > 1, F.element_at("sums", F.greatest(F.col("at") - 1, F.lit(1)))).otherwise(F.lit(0.0))
    first = one_by_one.withColumn("copies", (crossed(F.element_at("sums", F.col("at"))) - crossed(before)).cast("long"))

    small = sized.where(~is_large).drop("source_size").join(classes.select("key", "none", "class", "held"), ["key", "none", "class"])
    small = small.withColumn("part", F.col("draw") % F.ceil(F.col("held") / F.lit(PART_ROWS)))
    parts = small.groupBy("key", "none", "class", "part").agg(F.count(F.lit(1)).alias("n")).withColumn("some", F.expr(f"part DIV {PARTS}"))
    earlier = W.partitionBy("key", "none").orderBy(F.desc("class"), "some").rowsBetween(W.unboundedPreceding, -1)
    sums = parts.groupBy("key", "none", "class", "some").agg(F.sum("n").alias("n")).withColumn("start", F.coalesce(F.sum("n").over(earlier), F.lit(0))).drop("n")
    inside = W.partitionBy("key", "none", "class", "some").orderBy("part").rowsBetween(W.unboundedPreceding, -1)
    starts = parts.withColumn("inside", F.coalesce(F.sum("n").over(inside), F.lit(0))).join(sums, ["key", "none", "class", "some"])
    starts = starts.select("key", "none", "class", "part", (F.col("start") + F.col("inside")).alias("before")).join(placed.drop("sums"), ["key", "none"])
    within = W.partitionBy("key", "none", "class", "part").orderBy(F.desc("size"), F.col("doc_id").asc_nulls_first())
    ranked = small.join(starts, ["key", "none", "class", "part"]).withColumn("rank", F.col("before") + F.row_number().over(within))
    at = lambda rank: crossed(F.col("upto") + rank.cast("double") * F.col("rest"))
    others = ranked.withColumn("copies", (at(F.col("rank")) - at(F.col("rank") - 1)).cast("long"))
    return first.select(*columns).unionByName(others.select(*columns))


def mixed(docs: DataFrame) -> DataFrame:
    """The documents as the mix takes them, repeated by their copies; all columns as they are.

    Rows that repeat an id are drawn one by one; each gets the sum of its id's copies divided as evenly as whole copies allow, in the order of a hash of all their columns, so reruns agree.
    So do rows with a null id that agree in source and size, as nothing else names their draws. An empty table gives no rows.
    """
    number, rows, draws, copies = (unused(docs, c) for c in ("number", "rows", "draws", "copies"))
    keys = {unused(docs, c): c for c in ("id", "unnamed", "source", "size")}
    unnamed = F.col("doc_id").isNull()
    named = dict(
        zip(
            keys,
            (
                F.coalesce("doc_id", F.lit(0)), F.when(unnamed, F.when(F.col("source").isNull(), 2).otherwise(1)).otherwise(0), F.when(unnamed, F.coalesce("source", F.lit(""))).otherwise(F.lit("")),
                F.when(unnamed, _words()).otherwise(F.lit(0)).cast("long"),
            ),
            strict=True,
        )
    )
    size = list(keys)[3]
    taken = mix(docs).withColumns(named | {size: F.when(unnamed, F.col("size")).otherwise(F.lit(0)).cast("long")}).groupBy(*keys).agg(F.sum("copies").alias(draws), F.count(F.lit(1)).alias(rows))
    taken = Stages(docs.sparkSession, "mixed").write(taken.where(F.col(draws) > 0))
    there = docs.withColumns(named)
    single = there.join(taken.where(F.col(rows) == 1), list(keys)).withColumn(copies, F.col(draws).cast("int"))
    # Only repeated ids are numbered, so no other text is sorted for it.
    order = F.xxhash64(*[F.col(f"`{c}`") for c in docs.columns])
    several = there.join(taken.where(F.col(rows) > 1), list(keys)).withColumn(number, F.row_number().over(W.partitionBy(*keys).orderBy(order)))
    share = F.floor(F.col(draws) / F.col(rows)) + F.when(F.col(number) <= F.col(draws) % F.col(rows), 1).otherwise(0)
    out = single.unionByName(several.withColumn(copies, share.cast("int")).drop(number))
    return out.withColumn(number, F.explode(F.array_repeat(F.lit(1), F.col(copies)))).select(*[F.col(f"`{c}`") for c in docs.columns])


SQL = r"""
WITH RECURSIVE t AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size FROM documents
), r AS (
  SELECT *, coalesce(source, '') AS key, (source IS NULL)::INT AS none,
    CASE WHEN size < 16 THEN size ELSE length(bin(size)) * 8 + ((size >> (length(bin(size)) - 4)::BIGINT) & 7) END AS class,
    ('0x' || substr(md5(concat_ws(':', doc_id, size)), 1, 8))::BIGINT AS draw FROM t
), s AS (SELECT key, none, sum(size)::BIGINT AS source_size FROM r GROUP BY ALL),
w AS (SELECT *, 1 + (row_number() OVER (ORDER BY none, key) - 1) % 3 AS w FROM s),
l AS (
  SELECT *, (sum(source_size) OVER () - coalesce(sum(3 * source_size) OVER b, 0))::DOUBLE / (sum(w) OVER () - coalesce(sum(w) OVER b, 0))::DOUBLE AS level FROM w
  WINDOW b AS (ORDER BY (3 * source_size)::DOUBLE / w, none, key ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)
), g AS (
  SELECT key, none, source_size, least((3 * source_size)::DOUBLE, max(level) OVER () * w) AS target, ('0x' || substr(md5(key || none::VARCHAR), 1, 4))::BIGINT::DOUBLE / 65536.0::DOUBLE AS o FROM l
), b AS (
  SELECT key, none, doc_id, source, size, row_number() OVER (PARTITION BY key, none ORDER BY size DESC, doc_id NULLS FIRST) AS pos
  FROM r JOIN g USING (key, none) WHERE size > 0 AND size * 512 >= source_size
), f AS (
  SELECT key, none, 0::BIGINT AS pos, 0::DOUBLE AS prior, 0::DOUBLE AS upto, 0::BIGINT AS taken, 0::BIGINT AS seen, source_size, target, o FROM g
  UNION ALL
  SELECT key, none, pos, prior, upto, taken + (floor(upto + o) - floor(prior + o))::BIGINT * size, seen + size, source_size, target, o FROM (
    SELECT f.key, f.none, b.pos, b.size, f.upto AS prior, f.upto + least(greatest((f.target - f.taken::DOUBLE) / (f.source_size - f.seen)::DOUBLE, 0::DOUBLE), 3::DOUBLE) AS upto,
      f.taken, f.seen, f.source_size, f.target, f.o
    FROM f JOIN b ON b.key = f.key AND b.none = f.none AND b.pos = f.pos + 1)
), z AS (
  SELECT key, none, upto, CASE WHEN source_size > seen THEN least(greatest((target - taken::DOUBLE) / (source_size - seen)::DOUBLE, 0::DOUBLE), 3::DOUBLE) ELSE 0 END AS rest
  FROM f QUALIFY row_number() OVER (PARTITION BY key, none ORDER BY pos DESC) = 1
), h AS (SELECT key, none, class, count(*) AS held FROM r GROUP BY ALL),
k AS (
  SELECT r.doc_id, r.size, source_size, target, o, upto, rest,
    row_number() OVER (PARTITION BY key, none ORDER BY class DESC, draw % ceil(held / 128)::BIGINT, size DESC, doc_id NULLS FIRST) AS rank
  FROM r JOIN g USING (key, none) JOIN z USING (key, none) JOIN h USING (key, none, class) WHERE size = 0 OR size * 512 < source_size
)
SELECT doc_id, size, source_size, target, ((floor(upto + rank::DOUBLE * rest + o) - floor(upto + (rank - 1)::DOUBLE * rest + o))::BIGINT * size)::BIGINT AS taken FROM k
UNION ALL
SELECT b.doc_id, b.size, source_size, target, ((floor(f.upto + o) - floor(f.prior + o))::BIGINT * b.size)::BIGINT AS taken FROM b JOIN f USING (key, none, pos)
"""
