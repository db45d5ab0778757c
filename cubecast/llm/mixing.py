"""Mixing sources to target weights by exponential keys (weighted sampling without replacement).

Targets: the mix holds ``share`` times all sizes; sources share it by weight, none above ``cap`` times its
own size, the excess going to the others by weight until none is above (one row a source meets in one task there: sources are
few against documents; sums by source are made before). A source's whole epochs come
first: every document floor(target / source size) times. The rest of the target is drawn: each document
gets the key -ln(u) / w, with u from a hash of its identifier and w its quality weight, and documents are
taken in order of the key until the prefix sum of sizes meets the rest.

The prefix sum has two levels, so that a source with a third of all rows is no single task: sums by
(source, slot of u-order), prefix sums over the slots, then within one slot only. Quality weight: 2 for a
text with 4 to 11 code points a word on average, else 1 (or a given column).

Null text: size 0, taken 0 in the drawn part. Null source: last in the order of weights, a source of its own.
Null or repeated identifiers: their rows share a key, ordered by size; repeated rows are drawn alike, each with its
own place in the prefix sum. All sizes 0: targets 0. Very long texts are read once, by built-in functions. Empty table: empty
result. Other columns are ignored by ``mix`` and travel with their row, whatever their names, in ``mixed_documents``.
"""

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .tables import named

WORDS = r"[^\x20\x09-\x0D]+"
SLOTS = 4096


def sizes(docs: DataFrame, id_col: str, text_col: str, source_col: str, seed: int, carry: bool = False) -> DataFrame:
    """doc_id, named, known, size, key, slot, and the whole row if it is to be carried. The slot follows the order of the key.

    named, known: the source without nulls, so that windows and joins by it deal rows out alike.
    """
    size = F.coalesce(F.regexp_count(named(text_col), F.lit(WORDS)), F.lit(0)).cast("long")
    points = F.coalesce(F.length(named(text_col)), F.lit(0)).cast("long")
    source = named(source_col)
    digest = F.sha2(F.concat(F.lit(f"{seed}:"), F.coalesce(named(id_col).cast("string"), F.lit("null"))), 256)
    row = [F.struct(*map(named, docs.columns)).alias("row")] if carry else []
    u = (F.conv(F.substring(digest, 1, 12), 16, 10).cast("double") + F.lit(0.5)) / F.lit(float(2**48))
    return (
        docs.select(
            named(id_col).alias("doc_id"), F.coalesce(source.cast("string"), F.lit("")).alias("named"), source.isNotNull().alias("known"), size.alias("size"), points.alias("points"), u.alias("u"), *row
        )
        .withColumn("weight", F.when((F.col("points") >= 4 * F.col("size")) & (F.col("points") <= 11 * F.col("size")), 2.0).otherwise(1.0))
        .withColumn("key", -F.log("u") / F.col("weight"))
        .withColumn("slot", F.floor(-F.expm1(-F.col("key")) * SLOTS).cast("int"))
        .select("doc_id", "named", "known", "size", "key", "slot", *(["row"] if carry else []))
    )


def targets(totals: DataFrame, weights: list[float], share: float, cap: float) -> DataFrame:
    """source, source_size, target from source, source_size: one row a source.

    A source is at its cap when the level (what is left for it and the sources with larger cap / weight, by
    their weights) reaches its cap; in the order of cap / weight, the sources at their caps come first.
    """
    everything = Window.orderBy(F.col("source").asc_nulls_last())
    pick = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.row_number().over(everything) - 1, F.lit(len(weights))) + 1).cast("int"))
    t = totals.select("source", "source_size", pick.alias("w")).withColumn("most", F.lit(cap) * F.col("source_size"))
    order = Window.orderBy(F.col("most") / F.col("w"), F.col("source").asc_nulls_last())
    above, here = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing)
    whole = Window.partitionBy()
    t = (
        t.withColumn("left", F.lit(share) * F.sum("source_size").over(whole) - F.coalesce(F.sum("most").over(above), F.lit(0.0)))
        .withColumn("level", F.col("left") / F.sum("w").over(here))
        .withColumn("open", F.col("level") * F.col("w") < F.col("most"))
        .withColumn("level", F.min(F.when(F.col("open"), F.struct(F.col("most") / F.col("w"), F.col("level")))).over(whole).getField("level"))
    )
    return t.select("source", "source_size", F.coalesce(F.least("most", F.col("level") * F.col("w")), F.col("most")).alias("target"))


def mix(
    docs: DataFrame,
    weights: tuple[float, ...] = (5, 2, 1),
    share: float = 1.5,
    cap: float = 2.0,
    seed: int = 7,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
) -> DataFrame:
    """doc_id, size, source_size, target, taken of every row; source too."""
    kind = docs.schema[source_col].dataType
    out = planned(sizes(docs, id_col, text_col, source_col, seed), weights, share, cap)
    return out.select("doc_id", F.when(F.col("known"), F.col("named")).cast(kind).alias("source"), "size", "source_size", "target", "taken")


def planned(d: DataFrame, weights: tuple[float, ...], share: float, cap: float) -> DataFrame:
    """d with source_size, target, taken."""
    of = ["named", "known"]
    slots = d.groupBy(*of, "slot").agg(F.sum("size").alias("slot_size"))
    totals = slots.groupBy(*of).agg(F.sum("slot_size").alias("source_size"))
    totals = totals.select(F.when(F.col("known"), F.col("named")).alias("source"), "source_size")
    goal = targets(totals, list(weights), share, cap).withColumn("epochs", F.coalesce(F.floor(F.try_divide(F.col("target"), F.col("source_size"))), F.lit(0)).cast("long"))
    goal = goal.withColumn("rest", F.col("target") - F.col("epochs") * F.col("source_size"))
    goal = goal.select(F.coalesce("source", F.lit("")).alias("named"), F.col("source").isNotNull().alias("known"), "source_size", "target", "epochs", "rest")
    run = Window.partitionBy(*of).orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)
    start = slots.withColumn("before", F.coalesce(F.sum("slot_size").over(run), F.lit(0))).drop("slot_size")
    plan = start.join(goal, of)
    in_slot = Window.partitionBy(*of, "slot").orderBy("key", F.col("doc_id").asc_nulls_last(), "size").rowsBetween(Window.unboundedPreceding, 0)
    joined = d.withColumn("within", F.sum("size").over(in_slot)).join(plan, [*of, "slot"])
    reach = F.col("before") + F.col("within")
    # the document on the border is taken if its middle lies within the rest
    drawn = F.when(reach - F.col("size") / 2 <= F.col("rest"), F.col("size")).otherwise(F.lit(0))
    return joined.withColumn("taken", (F.col("epochs") * F.col("size") + drawn).cast("long"))


def mixed_documents(
    docs: DataFrame,
    weights: tuple[float, ...] = (5, 2, 1),
    share: float = 1.5,
    cap: float = 2.0,
    seed: int = 7,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
) -> DataFrame:
    """The rows of docs that the mix takes, repeated as often as it takes them, with their columns. A row of no words comes once."""
    out = planned(sizes(docs, id_col, text_col, source_col, seed, carry=True), weights, share, cap)
    times = F.when(F.col("size") > 0, F.expr("taken div size")).otherwise(F.lit(1)).cast("int")
    out = out.select("row", times.alias("times")).where("times > 0")
    return out.select(F.explode(F.array_repeat(F.lit(0), F.col("times"))), "row").select("row.*")


ORACLE = r"""
with d as (
  select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::bigint as size,
         coalesce(length(text), 0)::bigint as points,
         (('0x' || substr(sha256('7:' || coalesce(doc_id::varchar, 'null')), 1, 12))::bigint::double + 5e-1) / 281474976710656e0 as u
  from documents),
k as (select doc_id, source, size, -ln(u) / (case when points >= 4 * size and points <= 11 * size then 2e0 else 1e0 end) as key from d),
s as (select source, sum(size)::bigint as source_size, [5e0, 2e0, 1e0][((row_number() over (order by source nulls last) - 1) % 3 + 1)::int] as w from k group by source),
o as (select *, sum(w) over (order by 2 * source_size / w, source nulls last rows between current row and unbounded following) as ws,
       coalesce(sum(2 * source_size) over (order by 2 * source_size / w, source nulls last rows between unbounded preceding and 1 preceding), 0) as taken_up,
       sum(source_size) over () as everything from s),
l as (select min_by((15e-1 * everything - taken_up) / ws, 2 * source_size / w) as level from o where (15e-1 * everything - taken_up) / ws * w < 2 * source_size),
g as (select source, source_size, coalesce(least(2e0 * source_size, level * w), 2e0 * source_size) as target from o, l),
e as (select *, case when source_size > 0 then floor(target / source_size) else 0 end::bigint as epochs from g),
c as (select k.*, e.source_size, e.target, e.epochs, e.target - e.epochs * e.source_size as rest,
       sum(k.size) over (partition by k.source order by k.key, k.doc_id nulls last, k.size rows between unbounded preceding and current row) as reach
      from k join e on k.source is not distinct from e.source)
select doc_id, source, size, source_size, target,
       (epochs * size + case when reach - size / 2e0 <= rest then size else 0 end)::bigint as taken from c
"""
