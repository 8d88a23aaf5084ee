"""Mixing sources to target weights by Pareto order sampling.

Each source's target is its share of ``total`` by weight, held at ``cap`` times
its size, the excess going to the others by weight (the water-filling level
solves this in one pass over the sorted sources).  Within a source a document's
expected number of copies is in proportion to its odds, held at ``cap``, the
level again found by water-filling.  It is split into certain whole copies and
a fraction; the fractions are served by order sampling: documents rank by their
random odds over their inclusion odds, and the lowest ranks are taken until the
source's remaining target is met, to within half of the last document.

The random number of a document is a hash of its id and the seed, so reruns
and lost executors change nothing.  Odds are taken to sixteenths of an octave,
so a source has a bounded number of them.  A source's ranks are summed by
PARTS buckets, then the bucket in which its target falls by PARTS finer ones;
only the rows of the last one are put in order, about one in a million, so a
source with a third of all rows is no large group.  The sources themselves pass
through one task, a row each.

Null texts and texts without words have size 0 and may ride along at no cost;
a null source is a source of its own, last in code-point order; odds that are
null or not positive count as 1; repeated rows with one id share their rank and
are taken or left together; an empty table gives an empty mix.  Extra columns
pass through, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rowsketch.llm.common import named, text_or_empty, word_count
from rowsketch.shared import materialise

WEIGHTS = (3.0, 1.0, 2.0)
TOTAL_SHARE = 1.5
CAP = 2
#: Buckets of the rank scale, and of one of these again.
PARTS = 1024
#: Levels of odds in an octave.
LEVELS = 16
#: A table of sources up to this many rows is broadcast; a larger one is joined by key.
MOST_BROADCAST_ROWS = 20_000
UNIT = float(2**52)


def uniform(doc_id: Column, seed: int) -> Column:
    """52 bits of md5 as a number strictly between 0 and 1."""
    digits = F.substring(F.md5(F.concat_ws("|", F.coalesce(doc_id.cast("string"), F.lit("")), F.lit(str(seed))).cast("binary")), 1, 13)
    return (F.conv(digits, 16, 10).cast("long").cast("double") + 0.5) / UNIT


def targets(sources: DataFrame, weights=WEIGHTS, total_share: float = TOTAL_SHARE, cap: int = CAP) -> DataFrame:
    """(source, source_size) to (source, source_size, target).

    Level: the least L with sum(min(cap * size, L * weight)) = total.  Sources
    sorted by the level at which they fill up (cap * size / weight) fill in
    that order.  One row a source passes through the single-partition windows.
    """
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.pmod(F.col("_ord") - 1, F.lit(len(weights))) + 1).cast("int"))
    everything = Window.partitionBy(F.lit(0))
    fill = Window.partitionBy(F.lit(0)).orderBy("_full_at", "_ord")
    # nulls last; Spark sorts strings by their UTF-8 bytes, which is code-point order
    ranked = sources.select("*", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.col("source").asc_nulls_last())).alias("_ord"))
    ranked = ranked.select("*", w.alias("_w"), (F.lit(float(cap)) * F.col("source_size")).alias("_most"))
    ranked = ranked.select("*", (F.col("_most") / F.col("_w")).alias("_full_at"), (F.lit(total_share) * F.sum("source_size").over(everything)).alias("_total"))
    before = fill.rowsBetween(Window.unboundedPreceding, -1)
    ranked = ranked.select("*", F.coalesce(F.sum("_most").over(before), F.lit(0.0)).alias("_filled"), F.sum("_w").over(fill.rowsBetween(0, Window.unboundedFollowing)).alias("_w_left"))
    ranked = ranked.select("*", ((F.col("_total") - F.col("_filled")) / F.col("_w_left")).alias("_level_here"))
    # the first source, in filling order, that the level does not fill sets the level
    level = F.min(F.when(F.col("_level_here") <= F.col("_full_at"), F.struct("_full_at", "_ord", "_level_here"))).over(everything)["_level_here"]
    ranked = ranked.select("*", level.alias("_level"))
    return ranked.select("source", "source_size", F.coalesce(F.least("_most", F.col("_level") * F.col("_w")), F.col("_most")).alias("target"))


def _same_source(name: str = "source") -> Column:
    """Null sources join as one: a text no null maps to."""
    return F.struct(F.col(name).isNull().alias("n"), F.coalesce(F.col(name), F.lit("")).alias("s"))


def _rank(u: Column, pi: Column) -> Column:
    """Random odds over inclusion odds, brought to (0, 1) by q / (1 + q)."""
    q = (u / (1.0 - u)) / (pi / (1.0 - pi))
    return q / (1.0 + q)


def length_odds(text: str = "text") -> Column:
    """The production odds: texts of a hundred words and more are twice as likely, of a thousand and more four times."""
    size = word_count(text_or_empty(text))
    return F.when(size >= 1000, 4.0).when(size >= 100, 2.0).otherwise(1.0)


def _odds(weight: str | Column | None) -> Column:
    if weight is None:
        return F.lit(1.0)
    w = (named(weight) if isinstance(weight, str) else weight).cast("double")
    return F.when((w > 0) & (w < float("inf")), F.pow(F.lit(2.0), F.round(F.log2(w) * LEVELS) / LEVELS)).otherwise(1.0)


def plan_mix(docs: DataFrame, *, seed: int = 7, weights=WEIGHTS, total_share: float = TOTAL_SHARE, cap: int = CAP, text: str = "text", source: str = "source", doc_id: str = "doc_id", weight: str | Column | None = None) -> tuple[DataFrame, DataFrame]:
    """(slim, decided): slim rows (doc_id, source, size, _u, _w) and, by source, what to take.

    ``weight``, a column, raises a document's inclusion odds within its source;
    without it they are equal there and differ between sources.
    """
    slim = materialise(docs.select(named(doc_id).alias("doc_id"), named(source).cast("string").alias("source"), word_count(text_or_empty(text)).alias("size"), uniform(named(doc_id), seed).alias("_u"), _odds(weight).alias("_w")), "mix")
    levels = materialise(slim.groupBy("source", "_w").agg(F.sum("size").alias("size")).select("*", _same_source().alias("_key")), "mix-levels")
    per = levels.groupBy("source").agg(F.sum("size").alias("source_size"))
    goal = targets(per, weights, total_share, cap).select("*", _same_source().alias("_key"))
    # expected copies of a document: _scale * odds, at most cap; the highest odds reach it first
    joined = levels.select("_key", "_w", "size").join(goal, "_key")
    by_odds = Window.partitionBy("_key").orderBy(F.desc("_w"))
    filled = F.coalesce(F.sum("size").over(by_odds.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)) * cap
    open_ = F.sum(F.col("size") * F.col("_w")).over(by_odds.rowsBetween(0, Window.unboundedFollowing))
    joined = joined.select("*", ((F.col("target") - filled) / F.when(open_ > 0, open_)).alias("_here"))
    scale = F.max_by("_here", F.when(F.col("_here") * F.col("_w") <= F.lit(float(cap)), F.col("_w")))
    found = joined.groupBy("_key").agg(scale.alias("_found"), F.min("_w").alias("_least"), F.max("source_size").alias("_all"))
    scales = found.select("_key", F.when(F.col("_all") > 0, F.coalesce("_found", float(cap) / F.col("_least"))).otherwise(0.0).alias("_scale"))
    goal = materialise(goal.join(scales, "_key"), "mix-targets")
    ranked = _attach(slim, goal).select("*", *_split(cap))
    sums = ranked.groupBy("_key", "_coarse").agg(F.sum("size").alias("_size"), F.sum(F.col("size") * F.col("_whole")).alias("_sure"))
    sums = sums.select("*", (F.sum("_size").over(Window.partitionBy("_key").orderBy("_coarse")) - F.col("_size")).alias("_before"), F.sum("_sure").over(Window.partitionBy("_key")).alias("_sure_all"))
    left = materialise(sums.join(goal.select("_key", "target"), "_key").select("*", (F.col("target") - F.col("_sure_all")).alias("_left")), "mix-sums")
    inside, below = _edge(ranked, left, "_coarse")
    finer = inside.groupBy("_key", "_left", "_fine").agg(F.first("_before").alias("_start"), F.sum("size").alias("_size"))
    finer = finer.select("_key", "_left", "_fine", "_size", (F.col("_start") + F.sum("_size").over(Window.partitionBy("_key").orderBy("_fine")) - F.col("_size")).alias("_before"))
    last, finest = _edge(ranked, materialise(finer, "mix-finer"), "_fine")
    # equal ranks (repeated ids) are summed first, so that they stand or fall together
    last = last.groupBy("_key", "_rank", "_before", "_left").agg(F.sum("size").alias("_size"))
    upto = F.col("_before") + F.sum("_size").over(Window.partitionBy("_key").orderBy("_rank"))
    cut = last.select("_key", "_rank", (2.0 * upto - F.col("_size") <= 2.0 * F.col("_left")).alias("_in")).where("_in").groupBy("_key").agg(F.max("_rank").alias("_cut"))
    decided = goal.join(below.withColumnRenamed("_below", "_b1"), "_key", "left").join(finest.withColumnRenamed("_below", "_b2"), "_key", "left").join(cut, "_key", "left")
    upto_fine = F.greatest((F.coalesce("_b1", F.lit(-1)) + 1) * PARTS - 1, F.coalesce("_b2", F.lit(-1)))
    return slim, materialise(decided.select("_key", "source_size", "target", "_scale", upto_fine.alias("_below"), F.coalesce("_cut", F.lit(-1.0)).alias("_cut")), "mix-decided")


def _edge(ranked: DataFrame, sums: DataFrame, bucket: str) -> tuple[DataFrame, DataFrame]:
    """Rows of the bucket in which a source's target falls, and the last bucket that is taken whole."""
    edge = sums.where((F.col("_before") < F.col("_left")) & (F.col("_before") + F.col("_size") > F.col("_left"))).select("_key", bucket, "_before", "_left")
    below = sums.groupBy("_key").agg(F.max(F.when(F.col("_before") + F.col("_size") <= F.col("_left"), F.col(bucket))).alias("_below"))
    return ranked.join(_maybe_broadcast(edge), ["_key", bucket]), below


def _maybe_broadcast(table: DataFrame) -> DataFrame:
    return F.broadcast(table) if table.limit(MOST_BROADCAST_ROWS + 1).count() <= MOST_BROADCAST_ROWS else table


def _attach(rows: DataFrame, by_source: DataFrame) -> DataFrame:
    keyed = rows.select("*", _same_source().alias("_key"))
    return keyed.join(_maybe_broadcast(by_source.drop("source")), "_key")


def _split(cap: int) -> list[Column]:
    """Whole copies, rank of the fraction and its buckets."""
    copies = F.least(F.col("_scale") * F.col("_w"), F.lit(float(cap)))
    whole = F.floor(copies).cast("long")
    pi = copies - F.floor(copies)
    rank = F.when(pi > 0, _rank(F.col("_u"), pi)).otherwise(F.lit(1.0))
    fine = F.floor(rank * (PARTS * PARTS)).cast("long")
    return [whole.alias("_whole"), rank.alias("_rank"), fine.alias("_fine"), F.floor(fine / PARTS).cast("long").alias("_coarse")]


def _copies(rows: DataFrame, decided: DataFrame, cap: int) -> DataFrame:
    joined = _attach(rows, decided).select("*", *_split(cap))
    extra = ((F.col("_fine") <= F.col("_below")) | (F.col("_rank") <= F.col("_cut"))) & (F.col("_rank") < 1.0) & (F.col("_whole") < cap)
    return joined.select("*", (F.col("_whole") + F.when(extra, 1).otherwise(0)).alias("_copies"))


def mix_report(docs: DataFrame, *, seed: int = 7, cap: int = CAP, **options) -> DataFrame:
    """Per document: doc_id, size, source_size, target and taken (words the mix takes)."""
    slim, decided = plan_mix(docs, seed=seed, cap=cap, **options)
    return _copies(slim, decided, cap).select("doc_id", "source", "size", "source_size", "target", (F.col("size") * F.col("_copies")).alias("taken"))


def mix(docs: DataFrame, *, seed: int = 7, cap: int = CAP, doc_id: str = "doc_id", source: str = "source", weight: str | Column | None = None, **options) -> DataFrame:
    """The mixed documents themselves, a row for each copy taken, with the input's columns."""
    _, decided = plan_mix(docs, seed=seed, cap=cap, doc_id=doc_id, source=source, weight=weight, **options)
    body = docs.select(F.struct(*[named(c) for c in docs.columns]).alias("_doc"), named(source).cast("string").alias("source"), uniform(named(doc_id), seed).alias("_u"), _odds(weight).alias("_w"))
    taken = _copies(body, decided, cap).where("_copies > 0")
    return taken.select("_doc", F.explode(F.expr("sequence(1L, _copies)")).alias("_copy")).select("_doc.*")


def oracle(seed: int = 7) -> str:
    """DuckDB SQL for the report with the production parameters and odds."""
    return f"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size,
                  (('0x' || substr(md5(coalesce(doc_id::VARCHAR, '') || '|{seed}'), 1, 13))::BIGINT::DOUBLE + 0.5) / {UNIT!r} AS u FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
o AS (SELECT *, row_number() OVER (ORDER BY source COLLATE "binary" ASC NULLS LAST) AS ord, {float(CAP)} * source_size AS most, {TOTAL_SHARE} * (sum(source_size) OVER ()) AS total FROM s),
w AS (SELECT *, CAST([{", ".join(map(str, WEIGHTS))}][((ord - 1) % {len(WEIGHTS)}) + 1] AS DOUBLE) AS w FROM o),
f AS (SELECT *, most / w AS full_at FROM w),
l AS (SELECT *, (total - coalesce(sum(most) OVER (ORDER BY full_at, ord ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0))
                / (sum(w) OVER (ORDER BY full_at, ord ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)) AS here FROM f),
v AS (SELECT arg_min(here, struct_pack(a := full_at, b := ord)) AS level FROM l WHERE here <= full_at),
t AS (SELECT source, source_size, coalesce(least(most, level * w), most) AS target FROM l LEFT JOIN v ON true),
e AS (SELECT *, CASE WHEN size >= 1000 THEN 4.0::DOUBLE WHEN size >= 100 THEN 2.0::DOUBLE ELSE 1.0::DOUBLE END AS odds_in FROM d),
b AS (SELECT source, odds_in, sum(size) AS size FROM e GROUP BY source, odds_in),
h AS (SELECT b.source, odds_in, t.source_size,
             (target - {CAP} * coalesce(sum(size) OVER (PARTITION BY b.source ORDER BY odds_in DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
             / nullif(sum(size * odds_in) OVER (PARTITION BY b.source ORDER BY odds_in DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING), 0) AS here
      FROM b JOIN t ON b.source IS NOT DISTINCT FROM t.source),
z AS (SELECT source, CASE WHEN max(source_size) > 0 THEN coalesce(arg_max(here, odds_in) FILTER (WHERE here * odds_in <= {float(CAP)}), {float(CAP)} / min(odds_in)) ELSE 0.0 END AS scale FROM h GROUP BY source),
c AS (SELECT e.*, source_size, target, least(scale * odds_in, {float(CAP)}) AS copies
      FROM e JOIN t ON e.source IS NOT DISTINCT FROM t.source JOIN z ON e.source IS NOT DISTINCT FROM z.source),
q AS (SELECT *, floor(copies) AS whole, copies - floor(copies) AS pi,
             CASE WHEN copies > floor(copies) THEN (u / (1.0 - u)) / ((copies - floor(copies)) / (1.0 - (copies - floor(copies)))) END AS odds FROM c),
p AS (SELECT *, CASE WHEN odds IS NOT NULL THEN odds / (1.0 + odds) ELSE 1.0 END AS rank, target - sum(size * whole) OVER (PARTITION BY source) AS left_over FROM q),
g AS (SELECT source, rank, sum(size) AS size, any_value(left_over) AS left_over FROM p GROUP BY source, rank),
k AS (SELECT source, max(rank) AS cut FROM (SELECT *, sum(size) OVER (PARTITION BY source ORDER BY rank) AS upto FROM g) WHERE rank < 1.0 AND 2.0 * upto - size <= 2.0 * left_over GROUP BY source)
SELECT doc_id, size, source_size, round(target, 3) AS target,
       (size * (whole + CASE WHEN p.rank <= coalesce(cut, -1.0) AND whole < {CAP} THEN 1 ELSE 0 END))::BIGINT AS taken
FROM p LEFT JOIN k ON p.source IS NOT DISTINCT FROM k.source
"""
