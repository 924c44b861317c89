"""Mixing sources to target weights by pivotal dependent rounding. DataFrame functions only.

Every source gets a target number of words (``source_targets``). A document's copies then have the
mean target / source size: whole copies for sure, and a fraction p. The fractions are settled by
pivotal rounding: two documents exchange word mass (p times words) so that their sum stays the same,
in a random direction with odds that keep each mean, until one of them is at 0 or 1; the other goes
on. Documents are folded in buckets of a few dozen, the buckets' residuals in buckets again, and so
on up a tree, until one residual for each source is settled by a coin. So each source's words miss
the target by less than one document's words; units of one bucket are then turned around, the
largest first, as far as that brings the source nearer.

Cases: null text or size counts 0 words, a document of 0 words is settled by its own coin; a null
source is a source, ordered last; a source without words has target 0; rows that agree in source,
doc_id and size form one unit whose copies are dealt out evenly among them; a null doc_id is an
ordinary value; ties don't matter as units are ordered by hash, then doc_id, then size; an empty
table gives an empty result. Randomness comes from hashes of the seed, so reruns agree.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from prefixcode.llm.common import cut, n_words, table

WEIGHTS = (3.0, 1.0, 2.0)
SHARE = 1.5
MOST = 2.0
FOLD = 64  # units folded in one bucket, in the mean
SEED = 20


def source_targets(sources: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """source, source_size -> the same rows and target.

    target = min(most * size, level * weight) with the level at which targets sum to share * all
    sizes: what sharing out again and again converges to. With sources in order of size / weight the
    level is found by prefix sums, without iteration.
    """
    by_code = W.orderBy(F.col("source").asc_nulls_last())
    by_ratio = W.orderBy("__ratio", F.col("source").asc_nulls_last())
    everything = W.partitionBy()
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.row_number().over(by_code) - 1, F.lit(len(weights))) + 1).cast("int"))
    x = (
        sources.withColumn("__weight", weight)
        .withColumn("__most", F.col("source_size") * F.lit(most))
        .withColumn("__ratio", F.col("__most") / F.col("__weight"))
        .withColumn("__sum", F.sum(F.col("source_size").cast("double")).over(everything) * share)
        .withColumn("__before", F.coalesce(F.sum("__most").over(by_ratio.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("__left", F.sum("__weight").over(by_ratio.rowsBetween(0, W.unboundedFollowing)))
        .withColumn("__level", (F.col("__sum") - F.col("__before")) / F.col("__left"))
        .withColumn("__first", F.min(F.when(F.col("__level") <= F.col("__ratio"), F.struct("__ratio", "__level"))).over(everything)["__level"])
    )
    target = F.least(F.col("__most"), F.coalesce(F.col("__first") * F.col("__weight"), F.col("__most")))
    return x.withColumn("target", target).select(*sources.columns, "target")


def _coin(*cols: Column) -> Column:
    """A number in [0, 1) from a hash."""
    return (F.xxhash64(*cols).bitwiseAND(F.lit((1 << 53) - 1))).cast("double") / F.lit(float(1 << 53))


def _fold(units: Column, level: int) -> Column:
    """array<struct<key, doc_id, size, m, whole, p>> -> struct<done: array<...>, rest: one of them>.

    In done, p is 0 or 1.
    """

    def step(state: Column, b: Column) -> Column:
        a = state["rest"]
        up = F.least((1 - a["p"]) * a["size"], b["p"] * b["size"])  # mass that b can give to a
        down = F.least(a["p"] * a["size"], (1 - b["p"]) * b["size"])
        rise = _coin(F.lit(SEED + 1), F.lit(level), a["key"], a["doc_id"], b["key"], b["doc_id"]) * (up + down) < down
        a_up, b_up = a["p"] + up / a["size"], b["p"] - up / b["size"]
        a_down, b_down = a["p"] - down / a["size"], b["p"] + down / b["size"]
        ends_a_up = (1 - a["p"]) * a["size"] <= b["p"] * b["size"]
        ends_a_down = a["p"] * a["size"] <= (1 - b["p"]) * b["size"]
        clip = lambda p: F.greatest(F.lit(0.0), F.least(F.lit(1.0), p))
        done = F.when(rise, F.when(ends_a_up, a.withField("p", F.lit(1.0))).otherwise(b.withField("p", F.lit(0.0)))).otherwise(
            F.when(ends_a_down, a.withField("p", F.lit(0.0))).otherwise(b.withField("p", F.lit(1.0)))
        )
        rest = F.when(rise, F.when(ends_a_up, b.withField("p", clip(b_up))).otherwise(a.withField("p", clip(a_up)))).otherwise(
            F.when(ends_a_down, b.withField("p", clip(b_down))).otherwise(a.withField("p", clip(a_down)))
        )
        return F.struct(F.concat(state["done"], F.array(done)).alias("done"), rest.alias("rest"))

    first = F.element_at(units, 1)
    return F.aggregate(F.slice(units, F.lit(2), F.size(units)), F.struct(F.slice(units, 1, 0).alias("done"), first.alias("rest")), step)


def _even_out(done: Column, over: Column) -> Column:
    """Turn settled units of one bucket around, the largest first, while that brings a source nearer
    to its target. over: words that the last coin added to the source."""

    def step(state: Column, u: Column) -> Column:
        off = (u["p"] == 1) & (state["over"] >= u["size"])
        on = (u["p"] == 0) & (-state["over"] >= u["size"])
        turned = u.withField("p", F.when(off, F.lit(0.0)).when(on, F.lit(1.0)).otherwise(u["p"]))
        over = state["over"] + (turned["p"] - u["p"]) * u["size"]
        return F.struct(F.concat(state["done"], F.array(turned)).alias("done"), over.alias("over"))

    by_size = F.array_sort(done, lambda a, b: F.when(a["size"] != b["size"], F.signum(b["size"] - a["size"]).cast("int")).when(a["key"] < b["key"], -1).when(a["key"] > b["key"], 1).otherwise(0))
    return F.aggregate(by_size, F.struct(F.slice(done, 1, 0).alias("done"), over.alias("over")), step, lambda s: s["done"])


_UNIT = ("key", "doc_id", "size", "m", "whole", "p")


def copies(rows: DataFrame, fold: int = FOLD) -> tuple[DataFrame, DataFrame]:
    """rows: doc_id, source, size (a row for each document).

    Gives (units, sources). units: source, doc_id, size, m (rows that agree in these), copies (that
    the m rows get together), source_size, target. sources: source, source_size, target.
    """
    kept = cut(rows.groupBy("source", "doc_id", "size").agg(F.count(F.lit(1)).alias("m")), "mix-units")
    sums = kept.groupBy("source").agg(F.sum(F.col("size") * F.col("m")).alias("source_size"), F.count(F.lit(1)).alias("__n"))
    sources = cut(source_targets(sums), "mix-sources")
    most = sources.agg(F.max("__n")).first()[0] or 0
    mass = F.col("m") * F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    units = (
        kept.withColumnRenamed("source", "__source")
        .join(sources, F.col("__source").eqNullSafe(F.col("source")))
        .withColumn("key", F.xxhash64(F.lit(SEED), "doc_id", "size"))
        .withColumn("whole", F.floor(mass + 1e-12).cast("long"))
        .withColumn("p", F.greatest(F.lit(0.0), mass - F.col("whole")))
        .withColumn("__bucket", F.pmod(F.xxhash64(F.lit(SEED + 2), "doc_id", "size"), F.ceil(F.col("__n") / F.lit(fold)).cast("long")))
    )
    keep = ["source", *_UNIT]
    trivial = units.where((F.col("size") == 0) | (F.col("p") == 0)).select(*keep).withColumn("p", (_coin(F.lit(SEED + 3), F.col("key"), F.col("doc_id")) < F.col("p")).cast("double"))
    parts = [trivial]
    level, width = 0, -(-most // fold)
    open_units = units.where((F.col("size") > 0) & (F.col("p") > 0)).select(*keep, "__bucket")
    while True:
        folded = (
            open_units.groupBy("source", "__bucket")
            .agg(F.sort_array(F.collect_list(F.struct(*_UNIT))).alias("__units"))
            .select("source", "__bucket", _fold(F.col("__units"), level).alias("__f"))
        )
        folded = cut(folded.select("source", "__bucket", F.col("__f.done").alias("done"), F.col("__f.rest").alias("rest")), f"mix-level{level}")
        if level:
            parts.append(folded.select("source", F.explode("done").alias("u")).select("source", "u.*"))
        else:
            lowest = folded
        if width <= 1:
            break
        width, level = -(-width // fold), level + 1
        open_units = folded.select("source", "rest.*", F.floor(F.col("__bucket") / F.lit(fold)).alias("__bucket"))
    root = folded.select("source", "rest.*").withColumn("__p", (_coin(F.lit(SEED + 4), F.col("key"), F.col("doc_id")) < F.col("p")).cast("double"))
    parts.append(root.withColumn("p", F.col("__p")))
    over = root.select(F.col("source").alias("__source"), ((F.col("__p") - F.col("p")) * F.col("size")).alias("__over"))
    first = lowest.where("__bucket = 0").join(over, F.col("source").eqNullSafe(F.col("__source")), "left")
    first = first.withColumn("done", _even_out(F.col("done"), F.coalesce(F.col("__over"), F.lit(0.0))))
    for part in (lowest.where("__bucket > 0"), first):
        parts.append(part.select("source", F.explode("done").alias("u")).select("source", "u.*"))
    settled = parts[0].select(*keep)
    for part in parts[1:]:
        settled = settled.unionByName(part.select(*keep))
    settled = settled.withColumn("copies", F.col("whole") + F.col("p").cast("long")).withColumnRenamed("source", "__source")
    out = settled.join(sources, F.col("__source").eqNullSafe(F.col("source"))).select("source", "doc_id", "size", "m", "copies", "source_size", "target")
    return out, sources.select("source", "source_size", "target")


def _share(index: Column) -> Column:
    """Copies of the row with this index (from 0) among the m rows of a unit."""
    return F.floor((F.col("copies") + index) / F.col("m")).cast("long")


def mixed(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, size, source_size, target, taken, source, copies."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), n_words(docs["text"].cast("string")).alias("size"))
    units, _ = copies(rows)
    index = F.explode(F.sequence(F.lit(0), F.col("m") - 1)).alias("__i")
    return (
        units.select("*", index)
        .withColumn("copies", _share(F.col("__i")))
        .withColumn("taken", F.col("copies") * F.col("size"))
        .select("doc_id", "size", "source_size", "target", "taken", "source", "copies")
    )


def mix_documents(docs: DataFrame) -> DataFrame:
    """The mixture itself: each row of docs as often as it has copies, with its own columns only."""
    cols = docs.columns
    x = docs.select(F.struct(*cols).alias("__row"), F.col("doc_id").cast("long").alias("__id"), F.col("source").cast("string").alias("__src"), n_words(docs["text"].cast("string")).alias("__size"))
    units, _ = copies(x.select(F.col("__id").alias("doc_id"), F.col("__src").alias("source"), F.col("__size").alias("size")))
    units = cut(units, "mix-copies")
    same = (F.col("__id").eqNullSafe(F.col("doc_id"))) & (F.col("__src").eqNullSafe(F.col("source"))) & (F.col("__size") == F.col("size"))
    single = units.where("m = 1 and copies > 0")
    out = x.join(single.hint("merge"), same).select("__row", F.col("copies").alias("__n"))
    if units.where("m > 1").limit(1).count():
        several = units.where("m > 1")
        order = W.partitionBy("__id", "__src", "__size").orderBy(F.xxhash64("__row"))
        dealt = x.join(several, same).withColumn("__n", _share(F.row_number().over(order) - 1))
        out = out.unionByName(dealt.where("__n > 0").select("__row", "__n"))
    return out.withColumn("__k", F.explode(F.sequence(F.lit(1), F.col("__n")))).select("__row.*")


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixed(table(spark, sf_dir, "documents"))
