"""Mixing sources to target weights, in DataFrame functions alone.

Each source's documents are laid end to end and packed into blocks of ``block`` words.  Every
output shard draws how many blocks it takes of each source: the whole part of its expectation,
the rest by multinomial draws (plain multinomial counts have the same mean, but leave a source of a few
hundred blocks several percent off its target).  A source's slots are numbered through all shards and mapped
through a pseudorandom permutation of its block numbers (swap-or-not, keyed by source and pass), so
that a pass takes every block once; slots and blocks meet in a join by block number.

Parameters: ``weights`` by rank of the source (code point order, null last, repeating), ``share``
of all words in the mix, ``ceiling`` times a source's words at most (the excess goes to the others
by weight), ``block``, ``shard`` slots per output shard, ``seed``.  All draws are hashes of the seed:
reruns agree.

No step holds a source together: packing runs in buckets of about ``BUCKET`` documents, and only
one row per source and bucket is numbered through.

Defined cases: null or blank texts have size 0 and give nothing; a source without words has target
0; null is a source; repeated rows are documents of their own; an empty table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .spans import doc_key, text_key
from .workspace import buckets as partitions, keep

BUCKET = 2048
ROUNDS = 20
RUN = 1024
WORD = r"[^\x20\x09-\x0D]+"


@dataclass(frozen=True)
class Recipe:
    weights: tuple[int, ...] = (3, 1, 2)
    share: float = 1.5
    ceiling: int = 2
    block: int = 128
    shard: int = 1 << 16
    seed: int = 20240131


def _unit(*parts: Column) -> Column:
    """A hash as a number in [0, 1)."""
    return F.shiftrightunsigned(F.xxhash64(*parts), 11) / F.lit(float(1 << 53))


def permuted(x: Column, n: Column, *key: Column) -> Column:
    """The image of ``x`` under a keyed permutation of 0 .. n-1: each round mirrors x or lets it be."""

    def step(at: Column, k: Column) -> Column:
        mirror = F.pmod(F.pmod(F.xxhash64(*key, k), n) - at, n)
        flip = F.xxhash64(*key, k, F.greatest(at, mirror), F.lit(7)).bitwiseAND(1) == 1
        return F.when(flip, mirror).otherwise(at)

    return F.aggregate(F.sequence(F.lit(1), F.lit(ROUNDS)), x.cast("long"), step)


def sized(docs: DataFrame) -> DataFrame:
    """Id, keys, source and size (words) of every row."""
    return docs.select("doc_id", doc_key().alias("k"), text_key().alias("th"), F.col("source").cast("string").alias("source"), F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("size"))


def source_targets(sizes: DataFrame, recipe: Recipe) -> DataFrame:
    """source, sid, source_size, target: shares by weight, held at the ceiling, the excess reshared.

    With sources in order of ceiling per weight, the level to which shares are filled is the largest
    of (what is left after the sources before) / (weights from here on)."""
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    ranked = per.withColumn("sid", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1)
    weights = F.array(*map(F.lit, recipe.weights))
    ranked = ranked.withColumn("weight", F.element_at(weights, (F.pmod("sid", F.lit(len(recipe.weights))) + 1).cast("int")).cast("double"))
    ranked = ranked.withColumn("most", (F.col("source_size") * recipe.ceiling).cast("double"))
    order = Window.orderBy(F.col("most") / F.col("weight"), "sid")
    before = F.coalesce(F.sum("most").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    rest = F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing))
    wanted = F.sum("source_size").over(Window.partitionBy()) * recipe.share
    level = ranked.withColumn("level", (wanted - before) / rest)
    target = F.least("most", F.max("level").over(Window.partitionBy()) * F.col("weight"))
    return level.withColumn("target", target).select("source", "sid", "source_size", "target")


def _packed(sizes: DataFrame, targets: DataFrame, n_docs: int, recipe: Recipe) -> tuple[DataFrame, DataFrame]:
    """Documents with their place in their bucket's stream, and the buckets' first block numbers."""
    buckets = max(16, n_docs // BUCKET)
    rows = sizes.join(targets, sizes.source.eqNullSafe(targets.source)).drop(targets.source)
    rows = rows.where("size > 0").withColumn("bucket", F.pmod(F.xxhash64(F.lit(recipe.seed), "k"), F.lit(buckets)))
    own = Window.partitionBy("sid", "bucket").orderBy("k", "th", "size")
    rows = rows.withColumns({"at": F.sum("size").over(own.rowsBetween(Window.unboundedPreceding, 0)) - F.col("size"), "rn": F.row_number().over(own)})
    filled = sizes.where("size > 0").withColumn("bucket", F.pmod(F.xxhash64(F.lit(recipe.seed), "k"), F.lit(buckets)))
    filled = filled.groupBy("source", "bucket").agg(F.sum("size").alias("words"))
    filled = filled.join(targets, filled.source.eqNullSafe(targets.source)).select("sid", "bucket", F.ceil(F.col("words") / recipe.block).cast("long").alias("n"), "target", "source_size")
    numbered = Window.partitionBy("sid").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    return rows, filled.withColumn("first", F.coalesce(F.sum("n").over(numbered), F.lit(0)))


def drawn_blocks(blocks: DataFrame, recipe: Recipe) -> DataFrame:
    """shard, slot, sid, block: the mix as slots of its shards (slot: number within its source)."""
    per = blocks.groupBy("sid").agg(F.sum("n").alias("n"), F.first("target").alias("target"), F.first("source_size").alias("source_size"))
    per = per.withColumn("draws", F.col("target") * F.col("n") / F.col("source_size"))
    all_ = F.sum("draws").over(Window.partitionBy())
    per = per.withColumn("shards", F.greatest(F.lit(1), F.ceil(all_ / recipe.shard)).cast("long"))
    per = per.withColumns({"expected": F.col("draws") / F.col("shards"), "slots": F.round(all_ / F.col("shards")).cast("long")})
    per = per.withColumns({"whole": F.floor("expected").cast("long"), "part": F.col("expected") - F.floor("expected")})
    cumulative = Window.orderBy("sid").rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy()
    per = per.withColumns({
        "low": F.coalesce(F.sum("part").over(cumulative), F.lit(0.0)) / F.greatest(F.sum("part").over(everything), F.lit(1e-300)),
        "open": F.col("slots") - F.sum("whole").over(everything),
    })
    per = per.withColumn("shard", F.explode(F.sequence(F.lit(0).cast("long"), F.col("shards") - 1)))
    # multinomial draws of what the whole parts leave open: a draw goes to the source whose interval it falls in
    throws = per.where("sid = 0").withColumn("r", F.explode(F.when(F.col("open") > 0, F.sequence(F.lit(1).cast("long"), F.col("open")))))
    throws = throws.select("shard", F.lit(None).cast("int").alias("sid"), _unit(F.lit(recipe.seed), F.col("shard"), F.col("r")).alias("low"))
    intervals = per.where("part > 0").select("shard", "sid", "low")
    along = Window.partitionBy("shard").orderBy("low", F.col("sid").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0)
    hits = intervals.unionByName(throws).withColumn("hit", F.last("sid", True).over(along)).where("sid is null and hit is not null")
    extra = hits.groupBy("shard", F.col("hit").alias("sid")).agg(F.count("*").alias("extra"))
    counts = per.join(extra, ["shard", "sid"], "left").withColumn("count", F.col("whole") + F.coalesce("extra", F.lit(0)))
    through = Window.partitionBy("sid").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.withColumn("base", F.coalesce(F.sum("count").over(through), F.lit(0)))
    # slots are made where their run is dealt to, so that few shards don't mean few tasks
    counts = counts.withColumn("end", F.least(F.col("base") + F.col("count"), F.col("n") * recipe.ceiling)).where("base < end")
    runs = counts.select("shard", "sid", "n", "end", F.explode(F.sequence(F.col("base"), F.col("end") - 1, F.lit(RUN).cast("long"))).alias("run"))
    runs = runs.repartition(partitions(counts.sparkSession), "sid", "run")
    slots = runs.select("shard", "sid", "n", F.explode(F.sequence(F.col("run"), F.least(F.col("run") + RUN, F.col("end")) - 1)).alias("slot"))
    lap, place = F.floor(F.col("slot") / F.col("n")).cast("long"), F.pmod("slot", "n")
    return slots.select("shard", "slot", "sid", permuted(place, F.col("n"), F.lit(recipe.seed), F.col("sid"), lap).alias("block"))


def mixed_pieces(docs: DataFrame, recipe: Recipe = Recipe()) -> tuple[DataFrame, DataFrame, DataFrame]:
    """All rows with size, source_size and target; the pieces (document, first word, words, times
    taken) of documents with words; and the slots of the mix."""
    sizes = keep(sized(docs), "mix-sizes")
    targets = source_targets(sizes, recipe)
    rows, buckets = _packed(sizes, targets, sizes.count(), recipe)
    slots = drawn_blocks(buckets, recipe)
    times = slots.groupBy("sid", "block").agg(F.count("*").alias("times"))
    b = F.lit(recipe.block)
    stop = F.col("at") + F.col("size")
    pieces = rows.join(buckets.select("sid", "bucket", "first"), ["sid", "bucket"])
    pieces = pieces.withColumn("j", F.explode(F.sequence(F.floor(F.col("at") / b), F.floor((stop - 1) / b))))
    begin, end = F.greatest("at", F.col("j") * b), F.least(stop, (F.col("j") + 1) * b)
    pieces = pieces.select("sid", "bucket", "rn", "doc_id", "k", "th", "size", "source_size", "target", (F.col("first") + F.col("j")).alias("block"), (begin - F.col("at")).alias("word"), (end - begin).alias("words"))
    pieces = pieces.join(times.hint("merge"), ["sid", "block"], "left").fillna(0, ["times"])
    everything = sizes.join(targets, sizes.source.eqNullSafe(targets.source)).drop(targets.source)
    return everything, pieces, slots


def mix_documents(docs: DataFrame, recipe: Recipe = Recipe()) -> DataFrame:
    """doc_id, size, source_size, target, taken of every row."""
    everything, pieces, _ = mixed_pieces(docs, recipe)
    taken = pieces.groupBy("sid", "bucket", "rn").agg(*(F.first(c).alias(c) for c in ("doc_id", "size", "source_size", "target")), F.sum(F.col("words") * F.col("times")).alias("taken"))
    names = ["doc_id", "size", "source_size", "target", "taken"]
    blank = everything.where("size = 0").withColumn("taken", F.lit(0).cast("long"))
    return taken.select(names).unionByName(blank.select(names))


def mixed_texts(docs: DataFrame, recipe: Recipe = Recipe()) -> DataFrame:
    """The mix as rows of ``docs``: a row for each time (first, second, ...) that words of the document
    are taken, with those words (the text as it was, if all are); n_chars follows, where it exists."""
    _, pieces, _ = mixed_pieces(docs, recipe)
    same = Window.partitionBy("k", "th").orderBy("sid", "bucket", "rn")
    per = pieces.groupBy("k", "th", "sid", "bucket", "rn").agg(F.first("size").alias("size"), F.sort_array(F.collect_list(F.struct("word", "words", "times"))).alias("parts"))
    per = per.withColumn("copy", F.row_number().over(same)).select("k", "th", "copy", "size", "parts")
    # the caller's columns travel in a struct, out of the way of those made here
    keyed = docs.select(doc_key().alias("k"), text_key().alias("th"), F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"))
    keyed = keyed.withColumn("copy", F.row_number().over(Window.partitionBy("k", "th").orderBy(F.lit(0))))
    rows = keyed.join(per.hint("merge"), ["k", "th", "copy"])
    rows = rows.withColumn("lap", F.explode(F.sequence(F.lit(1), F.lit(recipe.ceiling))))
    rows = rows.withColumn("parts", F.filter("parts", lambda p: p["times"] >= F.col("lap"))).where(F.size("parts") > 0)
    words = F.regexp_extract_all("row.text", F.lit(f"({WORD})"), F.lit(1))
    some = F.array_join(F.flatten(F.transform("parts", lambda p: F.slice(words, (p["word"] + 1).cast("int"), p["words"].cast("int")))), " ")
    whole = F.aggregate("parts", F.lit(0).cast("long"), lambda a, p: a + p["words"]) == F.col("size")
    rows = rows.withColumn("mixed", F.when(whole, F.col("row.text")).otherwise(some))
    made = {"text": F.col("mixed")}
    if "n_chars" in docs.columns:
        made["n_chars"] = F.length("mixed").cast(docs.schema["n_chars"].dataType)
    return rows.select(*(made.get(c, F.col("row")[c]).alias(c) for c in docs.columns))
