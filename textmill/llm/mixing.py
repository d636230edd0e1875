"""Mixing sources to target weights by pivotal dependent rounding, in SQL functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

#: Documents that one fold rounds; most times that a document is taken; repeating weights of the query.
FAN_IN, MOST_COPIES, WEIGHTS = 64, 3, (1, 2, 3)
#: Times the mean size of a source from which a row is very long, or long.
CLASSES = (4, 1)


def targets(sizes: DataFrame, most: int = MOST_COPIES) -> DataFrame:
    """(source, source_size, n, weight) -> the same with target: shares of the total by weight, at most `most` times
    source_size, the excess reshared by weight until none is above.

    That ends where target = min(most * size, level * weight) for one level; sources are filled in the order in which
    a rising level reaches their bound. One row per source passes through the window, not documents.
    """
    bound = F.col("source_size") * most
    order = Window.orderBy(bound / F.col("weight"), "weight", F.col("source").asc_nulls_last())
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy()
    left = F.sum("source_size").over(everything) - F.coalesce(F.sum(bound).over(before), F.lit(0))
    weights = F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0))
    # The level with the first sources at their bound rises as long as the next one's bound lies below it.
    level = F.max("level").over(everything)
    out = sizes.withColumn("level", left.cast("double") / weights.cast("double"))
    return out.withColumn("target", F.least(bound.cast("double"), level * F.col("weight"))).drop("level")


def _unit(*of: Column) -> Column:
    """A number in [0, 1) that depends on the values only."""
    return F.pmod(F.xxhash64(*of), F.lit(1 << 52)).cast("double") / F.lit(float(1 << 52))


def _fold(items: Column, salt: Column) -> Column:
    """Pivotal rounding of an array of (p, a, key): the carried item meets the next, mass p * a passes between them at
    random until the fraction of one is 0 or 1; that one is settled and the other is carried on.

    Returns (at, p, a, key) of the item carried last and `up`, the places of the items settled at 1.
    """
    zero = F.struct(F.lit(-1).alias("at"), F.lit(0.0).alias("p"), F.lit(1.0).alias("a"), F.lit(0).cast("long").alias("key"), F.lit(0).alias("next"), F.array().cast("array<int>").alias("up"))

    def step(s: Column, x: Column) -> Column:
        p, q = s["p"], x["p"]
        ratio = s["a"] / x["a"]
        raise_p = F.least(F.lit(1.0) - p, q / ratio)  # the carried item gains as much as the other can give
        lower_p = F.least(p, (F.lit(1.0) - q) / ratio)
        up = _unit(salt, s["key"], x["key"]) * (raise_p + lower_p) < lower_p
        moved = F.when(up, raise_p).otherwise(-lower_p)
        full = F.when(up, raise_p >= F.lit(1.0) - p).otherwise(lower_p >= p)  # whether the carried one is settled
        p2, q2 = p + moved, F.greatest(F.lit(0.0), F.least(F.lit(1.0), q - moved * ratio))
        i = s["next"]
        idle = q <= 0
        first = s["at"] < 0
        settled_up = F.when(full & up, F.array(s["at"])).when(~full & ~up, F.array(i)).otherwise(F.array().cast("array<int>"))
        keep = F.struct(s["at"].alias("at"), p.alias("p"), s["a"].alias("a"), s["key"].alias("key"), (i + 1).alias("next"), s["up"].alias("up"))
        take = F.struct(i.alias("at"), q.alias("p"), x["a"].alias("a"), x["key"].alias("key"), (i + 1).alias("next"), s["up"].alias("up"))
        meet = F.struct(
            F.when(full, i).otherwise(s["at"]).alias("at"), F.when(full, q2).otherwise(p2).alias("p"), F.when(full, x["a"]).otherwise(s["a"]).alias("a"),
            F.when(full, x["key"]).otherwise(s["key"]).alias("key"), (i + 1).alias("next"), F.concat(s["up"], settled_up).alias("up"),
        )
        return F.when(idle, keep).when(first, take).otherwise(meet)

    return F.aggregate(items, zero, step)


def _rounded(blocks: DataFrame, levels: int, fan_in: int) -> DataFrame:
    """(source, block, p, a) of the fractions left in the blocks -> (source, block, up): whether each is rounded up.

    A reduction tree: `fan_in` neighbouring blocks are folded into one fraction, which goes to the next level; the
    decision comes back down. The last fraction of a source is rounded by itself.
    """
    if levels <= 0:
        return blocks.select("source", "block", (_unit(F.lit(99), F.col("source"), F.col("block")) < F.col("p")).alias("up"))
    parent = F.floor(F.col("block") / fan_in).alias("parent")
    item = F.struct(F.col("block").alias("key"), F.col("p"), F.col("a"))
    groups = blocks.groupBy("source", parent).agg(F.sort_array(F.collect_list(item)).alias("items"))
    folded = groups.withColumn("f", _fold(F.col("items"), F.lit(levels)))
    above = _rounded(folded.select("source", F.col("parent").alias("block"), F.col("f.p").alias("p"), F.col("f.a").alias("a")), levels - 1, fan_in)
    above = above.select(F.col("source").alias("source_"), F.col("block").alias("parent_"), F.col("up").alias("last_up"))
    down = folded.join(above, F.col("source").eqNullSafe(F.col("source_")) & (F.col("parent") == F.col("parent_")))
    each = down.select("source", F.posexplode("items").alias("at", "item"), "f", "last_up")
    return each.select("source", F.col("item.key").alias("block"), (F.array_contains("f.up", F.col("at")) | ((F.col("f.at") == F.col("at")) & F.col("last_up"))).alias("up"))


def _taken(rows: DataFrame, levels: int, fan_in: int) -> DataFrame:
    """Rows with source, size, x (times wanted), blocks -> the same with copies, x rounded up or down."""
    names = rows.columns
    base = F.floor("x").cast("int")
    item = F.struct(
        (-F.col("size")).alias("order"), F.xxhash64("doc_id").alias("key"), F.when(F.col("size") > 0, F.col("x") - base).otherwise(F.lit(0.0)).alias("p"),
        F.greatest("size", F.lit(1)).cast("double").alias("a"), base.alias("base"), F.struct(*names).alias("row"),
    )
    ordered = F.expr("array_sort(items, (x, y) -> CASE WHEN x.order < y.order THEN -1 WHEN x.order > y.order THEN 1 WHEN x.key < y.key THEN -1 WHEN x.key > y.key THEN 1 ELSE 0 END)")
    blocks = rows.groupBy("source", F.pmod(F.xxhash64("doc_id", F.lit("block")), F.col("blocks")).alias("block")).agg(F.collect_list(item).alias("items")).withColumn("items", ordered)
    folded = blocks.withColumn("f", _fold(F.transform("items", lambda i: F.struct(i["p"].alias("p"), i["a"].alias("a"), i["key"].alias("key"))), F.lit(0)))
    up = _rounded(folded.select("source", "block", F.col("f.p").alias("p"), F.col("f.a").alias("a")), levels, fan_in)
    up = up.select(F.col("source").alias("source_"), F.col("block").alias("block_"), F.col("up").alias("last_up"))
    both = folded.join(up, F.col("source").eqNullSafe(F.col("source_")) & (F.col("block") == F.col("block_")))
    each = both.select(F.posexplode("items").alias("at", "i"), "f", "last_up")
    more = F.array_contains("f.up", F.col("at")) | ((F.col("f.at") == F.col("at")) & F.col("last_up"))
    return each.select("i.row.*", (F.col("i.base") + more.cast("int")).alias("copies"))


def mix_sizes(sized: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST_COPIES, fan_in: int = FAN_IN) -> DataFrame:
    """The rows of a table with doc_id, source and size, with source_size, target and copies (0 to `most`): how often
    the mix takes each.

    Columns named like an added one are replaced. Sources by code point, null last, weigh `weights` in turn and share
    all words. A row of a source of size s and target t is wanted t / s times: the whole part is taken and the
    fraction is rounded by pivotal steps that keep the words of the source. Rows go in three classes of size, the
    long ones first; what the rounding of one class leaves over or takes too much is added to the share of the next,
    so the words taken differ from the target by about one short row. Random numbers are hashes of doc_id, so a rerun
    agrees. Rows of size 0 are taken by the whole part; repeated rows are rows of their own; an empty table gives an
    empty result. Rows of a source are dealt to blocks of about `fan_in`, so no source meets in one task.
    """
    kept = [c for c in sized.columns if c not in ("source_size", "target", "copies")]
    names = ["doc_id", "source", "size", "row_"]  # all columns travel in one, so their names can't clash with those here
    sized = common.stored(sized.select("doc_id", "source", F.col("size").cast("long").alias("size"), F.struct(*kept).alias("row_")))
    per = common.stored(sized.groupBy("source").agg(F.coalesce(F.sum("size"), F.lit(0)).alias("source_size"), F.count("*").alias("n")))
    order = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*[F.lit(w) for w in weights]), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int")).cast("long")
    per = common.stored(targets(per.withColumn("weight", weight), most).drop("weight"))
    mean = F.col("source_size") / F.col("n")
    of = per.select(F.col("source").alias("source_"), "source_size", "target", "n")
    class_of = F.when(F.col("size") >= CLASSES[0] * mean, 0).when(F.col("size") >= CLASSES[1] * mean, 1).otherwise(2)
    rows = common.stored(sized.join(of, F.col("source").eqNullSafe(F.col("source_"))).withColumn("class_", class_of).drop("source_", "n"))
    share = rows.groupBy("source", "class_").agg(F.sum("size").alias("words"), F.count("*").alias("n"))
    share = common.stored(share)
    out, parts = None, []
    for c in range(3):
        largest = share.filter(F.col("class_") == c).agg(F.max("n")).first()[0]
        if not largest:
            continue
        levels, k = 0, -(-largest // fan_in)
        while k > 1:
            levels, k = levels + 1, -(-k // fan_in)
        here = share.groupBy("source").agg(F.sum(F.when(F.col("class_") >= c, F.col("words")).otherwise(0)).alias("words"), F.sum(F.when(F.col("class_") == c, F.col("n")).otherwise(0)).alias("n")).withColumnsRenamed({"source": "s1"})
        got = rows.sparkSession.createDataFrame([], "s2 string, got long")
        if out is not None:
            got = out.groupBy("source").agg(F.sum(F.col("copies") * F.col("size")).alias("got")).withColumnsRenamed({"source": "s2"})
        plan = here.join(got, F.col("s1").eqNullSafe(F.col("s2")), "left").select("s1", "words", F.coalesce("got", F.lit(0)).alias("got"), F.ceil(F.col("n") / fan_in).alias("blocks"))
        plan = common.stored(plan)  # a row per source, whose size Spark then knows: small ones are broadcast
        part = rows.filter(F.col("class_") == c).join(plan, F.col("source").eqNullSafe(F.col("s1")))
        x = F.when(F.col("words") > 0, F.greatest(F.lit(0.0), F.least(F.lit(float(most)), (F.col("target") - F.col("got")) / F.col("words")))).otherwise(F.lit(0.0))
        part = part.select(*names, "source_size", "target", x.alias("x"), "blocks")
        parts.append(common.stored(_taken(part, levels, fan_in).drop("x", "blocks")))
        out = parts[-1] if out is None else out.unionByName(parts[-1])
    if out is None:
        out = rows.withColumn("copies", F.lit(0))
    return out.select("row_.*", "source_size", "target", "copies")


def mix(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST_COPIES) -> DataFrame:
    """The mix itself: the rows of docs, all columns, each as often as mix_sizes() takes it by its number of words.

    Columns used: doc_id, source, text. Rows alike in doc_id and text share the copies that their sizes were given, as
    evenly as they can: they are numbered within tasks, and tasks by the rows of those before. A null text is taken
    never, a null doc_id or source is one of its own, an empty table stays empty, columns of any name are carried along.
    """
    text = F.coalesce("text", F.lit(""))
    key = [F.coalesce(F.col("doc_id").cast("long"), F.lit(-(2**62))).alias("k1_"), F.xxhash64(text, F.col("doc_id").isNull()).alias("k2_")]
    light = docs.select("doc_id", "source", common.n_words(F.col("text")).alias("size"), *key)
    copies = mix_sizes(light, weights, most).groupBy("k1_", "k2_").agg(F.count("*").alias("n_"), F.sum("copies").alias("times_"))
    copies = common.stored(copies.filter("times_ > 0"))
    keyed = docs.select(F.struct(*docs.columns).alias("row_"), *key)  # all columns travel in one, so their names can't clash
    once = common.dealt_join(keyed, copies.filter("n_ = 1"), "k1_", "k2_")
    alike = copies.filter("n_ > 1")
    if not alike.isEmpty():
        rows = common.stored(common.dealt_join(keyed, alike, "k1_", "k2_").withColumn("part_", F.spark_partition_id()))
        parts = rows.groupBy("k1_", "k2_", "part_").agg(F.count("*").alias("here_"))
        before = F.sum("here_").over(Window.partitionBy("k1_", "k2_").orderBy("part_").rowsBetween(Window.unboundedPreceding, -1))  # a row a task
        parts = parts.select("k1_", "k2_", "part_", F.coalesce(before, F.lit(0)).alias("before_"))
        number = F.row_number().over(Window.partitionBy("k1_", "k2_", "part_").orderBy(F.lit(1)))
        numbered = rows.withColumn("number_", number).join(parts, ["k1_", "k2_", "part_"])
        times = F.floor(F.col("times_") / F.col("n_")) + (F.col("before_") + F.col("number_") <= F.col("times_") % F.col("n_")).cast("int")
        once = once.unionByName(numbered.withColumn("times_", times).select(*once.columns))
    return once.filter("times_ > 0").select("row_", F.explode(F.sequence(F.lit(1), F.col("times_").cast("int"))).alias("copy_")).select("row_.*")


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    light = common.table(spark, sf_dir, "documents").select("doc_id", "source", common.n_words(F.col("text")).alias("size"))
    return mix_sizes(light).select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).cast("long").alias("taken"), "source", "copies")
