"""Mixing sources to target weights with nested histograms of a hash: no sort, no window over documents.

Every document has a 60-bit hash. Per source the sizes are summed by the hash's first ten bits; the prefix sums show the
bucket in which the source's budget ends. Only that bucket is split by the next ten bits, and so on. Documents below the
final bucket are in, those above it are out, and the few in it share what is left in proportion to their sizes.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from biblake.llm.base import column, whole_again, whole_rows
from biblake.operators.ranges import running
from biblake.session import durable, rekeyed

WORD = "[^\\x20\\x09-\\x0D]+"
BITS, LEVELS = 10, 6
WEIGHTS = (5, 2, 1)
#: Rows of one per source that are broadcast, after they have been counted; more are joined by exchange.
BROADCAST_SOURCES = 10_000


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("bigint")


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: float = 3.0) -> DataFrame:
    """(source, source_size, target): weights repeat over the sources by code point, null last; a target stops at ``most`` times
    its source's size and the excess goes to the others by weight until none is above.

    One row a source; sources are placed by ranges, so many of them never meet in one task. The level at which targets stop is found from
    the sources' ratios of limit to weight: with the k tightest sources stopped, each other gets (all - their limits) / (weight left)
    for each unit of weight.
    """
    last = F.col("source").isNull()
    rows = running(sizes.groupBy("source").agg(F.sum("size").alias("total")), [last, F.col("source")])
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.pmod("place", F.lit(len(weights))) + 1).cast("int"))
    rows = rows.select("source", "total", w.alias("weight"), (F.col("total") * F.lit(float(most))).alias("limit")).withColumn("ratio", F.col("limit") / F.col("weight"))
    rows = durable(running(rows, [F.col("ratio"), last, F.col("source")], sums={"stopped": "limit", "gone": "weight"}))
    everything, weight = rows.agg(F.sum("total"), F.sum("weight")).first()
    level = (F.lit(float(everything or 0)) - F.col("stopped")) / (F.lit(float(weight or 0)) - F.col("gone"))
    cut = rows.agg(F.max(F.when(F.col("ratio") >= level, level))).first()[0]
    unit = F.lit(cut) if cut is not None else F.col("ratio")
    return rows.select("source", F.col("total").alias("source_size"), F.least(F.col("limit"), F.col("weight") * unit).alias("target"))


def mix(documents: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", weights: tuple[int, ...] = WEIGHTS, most: float = 3.0) -> DataFrame:
    """Per row: key, source, size, source_size, target, whole (times all of it is taken), part (words of one more, partial taking), taken.

    A null text has no words and is never taken. The hash is of key and text, so reruns and other partitionings agree. Rows that repeat are
    hashed alike; where a source's budget ends among them they are numbered and take what is left in turn, so the source still meets its
    target to the word (which of the equal rows takes a word more is open). An empty table gives an empty result; a null source is one of its own.
    """
    rows = durable(documents.select(column(key).alias("key"), column(source).alias("source"), *_marks(key, text)))
    per, shift, n_sources, ties = thresholds(rows, weights, most)
    return _taken(rows, per, shift, n_sources, ties).select("key", "source", "size", "source_size", "target", "whole", _part().alias("part"), (F.col("whole") * F.col("size") + _part()).alias("taken"))


def _marks(key: str, text: str) -> list[Column]:
    return [n_words(column(text)).alias("size"), F.shiftrightunsigned(F.xxhash64(F.lit("mix"), column(key), column(text)), 64 - BITS * LEVELS).alias("h")]


def _per_source(rows: DataFrame, per: DataFrame, n_sources: int, how: str = "inner") -> DataFrame:
    """per has one row a source (column s); it is broadcast while the counted sources are few."""
    same = F.col("source").eqNullSafe(F.col("s"))
    return rows.join(F.broadcast(per), same, how) if n_sources <= BROADCAST_SOURCES else rows.join(rekeyed(per, "s"), same, how)


def thresholds(rows: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: float = 3.0) -> tuple[DataFrame, int, int, bool]:
    """One row a source: where in the hashes its last round ends (edge, room, held); the bits that edge leaves out; the number of sources;
    whether some edge holds more than one row."""
    goal = durable(targets(rows, weights, most))
    n_sources = goal.count()
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("bigint")
    left = F.round(F.col("target") - F.col("whole") * F.col("source_size")).cast("bigint")
    names = ["s", "source_size", "target", "whole"]
    state = goal.withColumnRenamed("source", "s").withColumn("whole", whole).select(*names, left.alias("room")).withColumns({"edge": F.lit(0).cast("bigint"), "held": F.col("source_size")})
    shift, most_rows = BITS * LEVELS, 2
    while shift and most_rows > 1:
        shift -= BITS
        at = rows.select("source", "size", F.shiftright("h", shift).alias("b"), F.shiftright("h", shift + BITS).alias("p"))
        if shift + BITS < BITS * LEVELS:
            at = _per_source(at, state.select("s", "edge"), n_sources).where("p = edge")
        #: at most 1,024 rows a source from here on
        fine = at.groupBy("source", "b").agg(F.sum("size").alias("n"), F.count("*").alias("rows"))
        run = Window.partitionBy("source").orderBy("b").rowsBetween(Window.unboundedPreceding, Window.currentRow)
        upto = fine.withColumn("upto", F.sum("n").over(run))
        ends = F.struct("b", (F.col("room") - (F.col("upto") - F.col("n"))).alias("room"), F.col("n").alias("held"), "rows")
        joined = state.select(*names, "room", "edge").join(upto, F.col("source").eqNullSafe(F.col("s")), "left")
        found = joined.groupBy(*names, "edge").agg(F.min(F.when(F.col("upto") > F.col("room"), ends)).alias("e"), F.max("b").alias("last"))
        #: with no bucket that ends beyond the room all of it fits: the edge is past the last bucket
        edge = F.coalesce("e.b", F.col("last") + 1, F.shiftleft("edge", BITS))
        state = durable(found.select(*names, edge.alias("edge"), F.coalesce("e.room", F.lit(0)).alias("room"), F.coalesce("e.held", F.lit(0)).alias("held"), F.coalesce("e.rows", F.lit(0)).alias("rows")))
        most_rows = state.agg(F.max("rows")).first()[0] or 0
    return state, shift, n_sources, most_rows > 1


def _taken(rows: DataFrame, per: DataFrame, shift: int, n_sources: int, ties: bool) -> DataFrame:
    """Adds to rows with source, size and h the source's row and ``place_in``: -1 below the edge, null above it, at the edge the words of its rows before."""
    out = _per_source(rows, per.drop("rows"), n_sources)
    b, before = F.shiftright("h", shift), F.lit(0).cast("bigint")
    if not ties:
        return out.withColumn("place_in", F.when(b < F.col("edge"), -1).when(b == F.col("edge"), before))
    edge = running(out.where(b == F.col("edge")), by=["s"], sums={"place_in": "size"}).drop("place")
    rest = out.where(b != F.col("edge")).withColumn("place_in", F.when(b < F.col("edge"), F.lit(-1).cast("bigint")))
    return rest.unionByName(edge.withColumn("place_in", F.col("place_in").cast("bigint")))


def _share(upto: str) -> str:
    """The words that the first rows of an edge take: its room in proportion, never rounded up."""
    return f"(CAST(room AS DECIMAL(38,0)) * ({upto}) div held)"


def _part() -> Column:
    """The words of a partial taking; those of an edge sum up to its room."""
    at_edge = F.expr(f"CASE WHEN held > 0 THEN CAST({_share('place_in + size')} - {_share('place_in')} AS BIGINT) ELSE 0 END")
    return F.when(F.col("place_in") < 0, F.col("size")).when(F.col("place_in") >= 0, at_edge).otherwise(F.lit(0)).cast("bigint")


def digest(documents: DataFrame) -> DataFrame:
    return mix(documents).select(F.col("key").alias("doc_id"), "size", "source_size", "target", "taken")


def mixed_documents(documents: DataFrame) -> DataFrame:
    """The documents of the mix, each as often as it is taken whole.

    Of the document at which a source's budget ends one more copy is taken if its partial taking is at least half of it; of rows that repeat there
    as many as what they take together comes to, rounded. Documents without a word go; an empty table gives an empty result.
    """
    names = documents.columns
    per, shift, n_sources, ties = thresholds(durable(documents.select("source", *_marks("doc_id", "text"))))
    kept = documents.select(whole_rows(documents).alias("doc"), "source", *_marks("doc_id", "text")).where("size > 0")
    #: whole copies that the first rows of an edge take, rounded
    copies = lambda upto: f"floor(CAST(room AS DOUBLE) * ({upto}) / held / size + 0.5)"
    extra = F.expr(f"CASE WHEN place_in < 0 THEN 1 WHEN place_in >= 0 AND held > 0 THEN {copies('place_in + size')} - {copies('place_in')} ELSE 0 END")
    out = _taken(kept, per, shift, n_sources, ties).withColumn("times", (F.col("whole") + extra).cast("int")).where("times > 0")
    return whole_again(out.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("times")))), "doc", names)
