"""Mixing sources to target weights: Pareto order sampling after certain whole copies.

Every document of a source is expected target / source_size times in the mix. The whole part of that number is taken as
certain copies; for the rest, with inclusion probability p, a document draws a keyed uniform u and gets the rank
(u / (1 - u)) / (p / (1 - p)). Documents are taken in rising rank until the words taken are as near as possible to what
the source still needs: a sample of fixed size in words, closed by the one document that fits what is missing best. ``odds_col`` gives documents of a source unequal probabilities:
p is proportional to it, held below one.

No source is ordered in one task: ranks fall into bins by their size, sums per bin (at most ``BINS`` a source) show the
bin that holds the cut, and only that bin is divided again, until its rows can be ordered. Draws depend on a seed, the
id and the text alone, so reruns agree.

Defined results: null texts have size 0; null sources are a source of their own, last in order; sources without words
have target 0; rows that are equal in id and text tie and are ordered as one run of equal rows; an empty table gives none.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common as C

BINS, ORDERED, LEVELS = 4096, 50_000, 8
TOKENS = r"[^\x20\x09-\x0D]+"


def word_count(text: Column) -> Column:
    """Number of runs without white space: blanks before a word are what is counted, without building the words.

    The line feeds that mark them are the only ones, as those of the text are blanks by then.
    """
    flat = F.translate(text, "\t\n\x0b\x0c\r", "     ")
    starts = F.regexp_replace(F.concat(F.lit(" "), flat), r" +(?=[^ ])", "\n")
    return F.coalesce((F.length(starts) - F.length(F.replace(starts, F.lit("\n"), F.lit("")))).cast("long"), F.lit(0).cast("long"))


def targets(sizes: DataFrame, weights: list[float], total_share: float, most: float) -> DataFrame:
    """source, source_size, target for a frame (source, source_size) of one row a source.

    With w the weight of a source and S its size, targets are min(most * S, w * level): sources with small S / w are
    full, the others share the rest by weight. A window over the sources, not over documents, finds the level.
    """
    order = Window.orderBy(F.col("source").isNull(), F.col("source"))
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int"))
    placed = sizes.withColumn("w", w)
    full = Window.orderBy(F.col("source_size") / F.col("w"), F.col("source").isNull(), "source").rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    rest = F.lit(total_share) * F.sum("source_size").over(every) - F.lit(most) * F.coalesce(F.sum("source_size").over(full), F.lit(0))
    share = rest / (F.sum("w").over(every) - F.coalesce(F.sum("w").over(full), F.lit(0.0)))
    # the first source, in that order, that isn't full at the level of those from it on gives the level of all of them
    levelled = placed.withColumn("level", share).withColumn("open", F.col("w") * F.col("level") <= F.lit(most) * F.col("source_size"))
    level = F.min_by(F.when(F.col("open"), F.col("level")), F.when(F.col("open"), F.col("source_size") / F.col("w"))).over(every)
    target = F.when(F.col("source_size") == 0, F.lit(0.0)).otherwise(
        F.least(F.lit(float(most)) * F.col("source_size"), F.coalesce(F.col("w") * level, F.lit(float(most)) * F.col("source_size")))
    )
    return levelled.withColumn("target", target).drop("w", "level", "open")


def _drawn(docs: DataFrame, o: dict, *keep: Column) -> DataFrame:
    """What the choice of a row depends on: source, id, code (of the text), size, odds and u; ``keep`` beside it."""
    text = F.coalesce(F.col(o["text_col"]), F.lit(""))
    rows = docs.select(
        *keep, F.col(o["source_col"]).alias("source"), F.col(o["id_col"]).alias("id"), F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long").alias("code"),
        *([word_count(text).alias("size")] if not keep or o["odds"] else []), *([F.col(o["odds_col"]).alias("given")] if o["odds_col"] else []),
    )
    odds = F.greatest(F.coalesce(F.col("given").cast("double"), F.lit(0.0)), F.lit(1e-6)) if o["odds_col"] else F.greatest(F.ceil(F.sqrt("size")), F.lit(1)) if o["odds"] else F.lit(1)
    return rows.withColumn("odds", odds.cast("decimal(18,6)")).withColumn("u", C.uniform(F.lit(o["seed"]), F.col("id"), F.col("code"))).drop("given")


def _planned(drawn: DataFrame, plan: DataFrame) -> DataFrame:
    """Adds the plan of a row's source and its ``rank``: Pareto odds, mapped to (0, 1); null where nothing is drawn."""
    joined = drawn.join(C.small(plan), F.col("source").eqNullSafe(F.col("p_source")), "left").drop("p_source")
    p = F.greatest(F.least(F.col("p_need") / F.greatest("p_size", F.lit(1)) * F.col("odds").cast("double") / F.col("p_odds"), F.lit(1 - 1e-9)), F.lit(1e-12))
    odds = (F.col("u") / (1 - F.col("u"))) / (p / (1 - p))
    return joined.withColumn("rank", F.when(F.col("p_need") > 0, F.least(odds / (1 + odds), F.lit(1 - 2.0**-53))))


def _copies() -> Column:
    """Copies of a row of :func:`_planned`: certain ones, one if it ranks up to the cut, one if it closes the gap."""
    before = F.coalesce(F.struct("rank", "id", "code") <= F.col("p_cut"), F.lit(False))
    closing = F.coalesce(F.struct("id", "code").eqNullSafe(F.col("p_close")) & F.col("p_close").isNotNull(), F.lit(False))
    return F.coalesce(F.col("p_whole"), F.lit(0).cast("long")) + (F.col("rank").isNotNull() & (before | closing)).cast("long")


def source_plan(docs: DataFrame, **options) -> DataFrame:
    """One row a source: p_source, p_size, p_target, p_whole, p_need, p_odds, p_cut and p_close.

    p_cut is the last (rank, id, code) taken by rank; p_close is the (id, code), of those not taken by rank, that comes
    nearest to what is then still missing.
    """
    o = OPTIONS | options
    return _plan(C.stored(_drawn(docs, o), "sizes"), o)


def _plan(drawn: DataFrame, o: dict) -> DataFrame:
    """The plan from the narrow stored table of :func:`_drawn`: all passes but the one that made it read no texts."""
    spread = F.try_divide(F.sum((F.col("odds") * F.col("size")).cast("decimal(38,6)")).cast("double"), F.sum("size"))
    sums = C.stored(drawn.groupBy("source").agg(F.sum("size").alias("source_size"), spread.alias("odds")), "sources")
    goal = targets(sums, o["weights"], o["total_share"], o["most"])
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    goal = goal.select(
        F.col("source").alias("p_source"), F.col("source_size").alias("p_size"), F.col("target").alias("p_target"), whole.alias("p_whole"),
        (F.col("target") - whole * F.col("source_size")).alias("p_need"), F.coalesce("odds", F.lit(1.0)).alias("p_odds"),
    )
    goal = C.stored(goal, "targets")
    ranked = _planned(drawn, goal).filter("size > 0 and p_need > 0")
    cut = C.stored(_cut(ranked), "cuts")
    rest = ranked.join(C.small(cut), F.col("source").eqNullSafe(F.col("c_source"))).filter(F.struct("rank", "id", "code") > F.col("p_cut"))
    gap = F.abs(F.col("size") - F.col("missing"))
    close = rest.filter(gap < F.col("missing")).groupBy(F.col("source").alias("d_source")).agg(F.min_by(F.struct("id", "code"), F.struct(gap, "rank", "id", "code")).alias("p_close"))
    out = goal.join(C.small(cut), F.col("p_source").eqNullSafe(F.col("c_source")), "left")
    out = out.join(C.small(C.stored(close, "closing")), F.col("p_source").eqNullSafe(F.col("d_source")), "left")
    return C.stored(out.drop("c_source", "d_source", "missing"), "plan")


def _cut(ranked: DataFrame) -> DataFrame:
    """c_source, p_cut, missing: the last (rank, id, code) with a running sum up to the need, and what is then missing.

    Level by level, bins of the rank narrow down to the one in which the sum of sizes passes the need, until no source has
    over ``ORDERED`` different rows left. Widths are powers of two and bounds their multiples, so no row falls between bins.
    """
    # rows with equal id and text are one run that is taken or left as a whole
    rows = ranked.groupBy("source", "rank", "id", "code").agg(F.sum("size").alias("size"), F.first("p_need").alias("need"))
    rows = rows.withColumns({"lo": F.lit(0.0), "base": F.lit(0).cast("long")})
    width, id_type = 1.0, ranked.schema["id"].dataType
    for k in range(LEVELS):
        width /= BINS
        level = rows.withColumn("bin", F.least(F.floor((F.col("rank") - F.col("lo")) / F.lit(width)), F.lit(BINS - 1)))
        sums = level.groupBy("source", "bin").agg(F.sum("size").alias("size"), F.count("*").alias("n"), F.first("need").alias("need"), F.first("lo").alias("lo"), F.first("base").alias("base"))
        upto = Window.partitionBy("source").orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
        passed = sums.withColumn("after", F.col("base") + F.sum("size").over(upto))
        # the last bin stands in where rounding keeps the sum of all below the need
        last = F.row_number().over(Window.partitionBy("source").orderBy(F.desc("bin"))) == 1
        found = passed.withColumn("last", last).filter((F.col("after") >= F.col("need")) | F.col("last")).groupBy("source").agg(
            F.min_by(F.struct((F.col("after") - F.col("size")).alias("base"), (F.col("lo") + F.col("bin") * F.lit(width)).alias("lo"), "need", "n"), "bin").alias("x")
        )
        state = C.stored(found.select(F.col("source").alias("c_source"), F.col("x.base").alias("c_base"), F.col("x.lo").alias("c_lo"), F.col("x.need").alias("c_need"), F.col("x.n").alias("c_n")), "bins")
        rows = rows.join(C.small(state), F.col("source").eqNullSafe(F.col("c_source"))).filter((F.col("rank") >= F.col("c_lo")) & (F.col("rank") < F.col("c_lo") + F.lit(width)))
        rows = rows.select("source", "rank", "id", "code", "size", "need", F.col("c_lo").alias("lo"), F.col("c_base").alias("base"))
        if (state.agg(F.max("c_n")).first()[0] or 0) <= ORDERED:
            break
        rows = C.stored(rows, "narrowed")
    order = Window.partitionBy("source").orderBy("rank", "id", "code").rowsBetween(Window.unboundedPreceding, 0)
    inside = rows.withColumn("after", F.col("base") + F.sum("size").over(order)).filter(F.col("after") <= F.col("need"))
    inside = inside.groupBy(F.col("source").alias("i_source")).agg(F.max(F.struct("rank", "id", "code")).alias("cut"), F.max("after").alias("sum"))
    # where even the first row of the bin is past the need, the rows below the bin are taken
    floor = F.struct(F.col("c_lo").alias("rank"), F.lit(None).cast(id_type).alias("id"), F.lit(None).cast("long").alias("code"))
    joined = state.join(C.small(C.stored(inside, "inside")), F.col("c_source").eqNullSafe(F.col("i_source")), "left")
    return joined.select("c_source", F.coalesce("cut", floor).alias("p_cut"), (F.col("c_need") - F.coalesce("sum", "c_base")).alias("missing"))


OPTIONS = {"id_col": "doc_id", "text_col": "text", "source_col": "source", "weights": [3.0, 1.0, 2.0], "total_share": 1.5, "most": 2.0, "seed": 17, "odds_col": None, "odds": None}


def plan_copies(docs: DataFrame, **options) -> DataFrame:
    """id, source, size, source_size, target and copies of every document. Options: see ``OPTIONS``. Texts are read once."""
    o = OPTIONS | options
    drawn = C.stored(_drawn(docs, o), "sizes")
    rows = _planned(drawn, _plan(drawn, o))
    return rows.select(F.col("id").alias(o["id_col"]), "source", "size", F.col("p_size").alias("source_size"), F.col("p_target").alias("target"), _copies().alias("copies"))


def mix(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with every row repeated as often as the mix takes it (0, 1 or more times); row-local but for the plan."""
    o = OPTIONS | options
    rows = _planned(_drawn(docs, o, F.struct("*").alias("row")), source_plan(docs, **options)).select("row", _copies().alias("n")).filter("n > 0")
    return rows.select("row", F.explode(F.sequence(F.lit(1).cast("long"), F.col("n")))).select("row.*")


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract digest: words that the mix takes of every document, its odds growing with the root of its size."""
    found = plan_copies(C.table(spark, sf_dir, "documents"), odds="size")
    return found.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


OP8_SQL = r"""
WITH d AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
    CAST(('0x' || substr(md5('17:' || doc_id || ':' || CAST(('0x' || substr(md5(coalesce(text, '')), 1, 15)) AS BIGINT)), 1, 13)) AS BIGINT) / 4503599627370496.0 AS u FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, CAST(sum(CAST(greatest(ceil(sqrt(size)), 1) AS HUGEINT) * size) AS DOUBLE) / nullif(sum(size), 0)::DOUBLE AS odds FROM d GROUP BY source),
w AS (SELECT *, CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 3.0::DOUBLE WHEN 1 THEN 1.0::DOUBLE ELSE 2.0::DOUBLE END AS w FROM s),
l AS (SELECT *, (1.5::DOUBLE * sum(source_size) OVER () - 2.0::DOUBLE * coalesce(sum(source_size) OVER f, 0)) / (sum(w) OVER () - coalesce(sum(w) OVER f, 0)) AS level
  FROM w WINDOW f AS (ORDER BY source_size / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
v AS (SELECT arg_min(level, source_size / w) AS level FROM l WHERE w * level <= 2.0::DOUBLE * source_size),
t AS (SELECT source, source_size, CASE WHEN source_size = 0 THEN 0.0::DOUBLE ELSE least(2.0::DOUBLE * source_size, coalesce(w * (SELECT level FROM v), 2.0::DOUBLE * source_size)) END AS target, odds FROM w),
n AS (SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS whole FROM t),
e AS (SELECT d.*, n.source_size, n.target, n.whole, n.target - n.whole * n.source_size AS need,
    greatest(least((n.target - n.whole * n.source_size) / greatest(n.source_size, 1) * greatest(ceil(sqrt(size)), 1) / n.odds, 1 - 1e-9::DOUBLE), 1e-12::DOUBLE) AS p
  FROM d JOIN n ON d.source IS NOT DISTINCT FROM n.source),
r AS (SELECT *, sum(CASE WHEN size > 0 THEN size ELSE 0 END) OVER (PARTITION BY source ORDER BY rank, doc_id ROWS UNBOUNDED PRECEDING) AS after
  FROM (SELECT *, u / (1 - u) / (p / (1 - p)) AS rank FROM e)),
m AS (SELECT source, any_value(need) - coalesce(max(CASE WHEN after <= need THEN after END), 0) AS missing FROM r WHERE size > 0 AND need > 0 GROUP BY source),
c AS (SELECT r.source, arg_min(doc_id, (abs(size - missing), rank, doc_id)) AS close FROM r JOIN m ON r.source IS NOT DISTINCT FROM m.source WHERE size > 0 AND need > 0 AND after > need AND abs(size - missing) < missing GROUP BY r.source)
SELECT r.doc_id, r.size, r.source_size, r.target, CAST(r.size * (whole + CASE WHEN need > 0 AND (after <= need OR coalesce(doc_id = close, FALSE)) THEN 1 ELSE 0 END) AS BIGINT) AS taken
FROM r LEFT JOIN c ON r.source IS NOT DISTINCT FROM c.source
"""
