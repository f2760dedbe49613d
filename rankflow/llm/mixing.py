"""Mixing sources to target weights by a low-discrepancy schedule.

Slot i of the schedule maps the golden-ratio point frac(i * 0.618...) through
the sources' cumulative targets to a source; its rank among that source's slots
names the block of equal size that fills it. A source's blocks cut the endless
repetition of its shuffled documents, so sources interleave evenly at every
prefix of the mix and small sources repeat while large ones are cut short.

All steps are DataFrame operations. Positions inside a source are prefix sums
in the order of a hash: sums by hash prefixes of two digits (256 rows a source),
of four within two (as many), and inside a prefix, so that no task sees a whole
source, however large. What
several steps read is written once, with a number for each row.

Null texts have no words; a null source is a source of its own, the last.
Documents without words are never taken. Texts count whole, however long. Rows
that repeat an id, or all of a row, are counted each; ties of the shuffled order
go by doc_id and size. An empty table gives an empty mix. Other columns are never
looked at, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import forget, free_names, staged, word_count

WEIGHTS = (5, 2, 1)
#: No source is repeated more often than this.
MOST_REPEATS = 3
#: Points are integers below 2 ** POINT_BITS; GOLDEN / 2 ** 31 is the golden ratio's fraction.
POINT_BITS, GOLDEN = 31, 1327217885
CELL_BITS = 10
SLOT_CHUNK_BITS = 12
#: Words of a block: the total over 2 ** 16, but within these bounds.
LEAST_BLOCK, MOST_BLOCK = 1, 2048
SEED = "mix-1"
FEW_SOURCES = 10_000


def document_sizes(docs: DataFrame, mark: Column | None = None) -> DataFrame:
    """doc_id, source, size (and mark): all that the mix needs of a document."""
    more = [mark.alias("mark")] if mark is not None else []
    return docs.select("doc_id", F.col("source").cast("string").alias("source"), word_count(F.col("text")).alias("size"), *more)


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, repeats: int = MOST_REPEATS) -> DataFrame:
    """sid, source, source_size, target and block (words a block) of each source.

    Targets share the total by weight; what exceeds ``repeats`` times a source's
    size goes to the others by weight, until none is above. That fixed point is
    least(cap, level * weight) for one level, found in one sorted pass.
    """
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    placed = per.withColumn("sid", F.row_number().over(W.orderBy(F.col("source").isNull(), "source")) - 1)
    weighed = placed.withColumn("w", F.element_at(F.array(*map(F.lit, weights)), (F.col("sid") % len(weights) + 1).cast("int"))).withColumn("cap", F.col("source_size") * repeats)
    order = W.orderBy(F.col("cap") / F.col("w"), "sid")
    all_rows = W.partitionBy().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    filled = (
        weighed.withColumn("total", F.sum("source_size").over(all_rows))
        .withColumn("below", F.coalesce(F.sum("cap").over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
        .withColumn("rest", F.sum("w").over(order.rowsBetween(0, W.unboundedFollowing)))
        .withColumn("level", (F.col("total") - F.col("below")) / F.col("rest"))
        .withColumn("fits", F.when(F.col("level") <= F.col("cap") / F.col("w"), F.struct(F.col("rest"), F.col("level"))))
        .withColumn("level", F.max("fits").over(all_rows)["level"])
    )
    block = F.greatest(F.lit(LEAST_BLOCK), F.least(F.lit(MOST_BLOCK), F.expr(f"total div {1 << 16}"))).cast("long")
    return filled.select("sid", "source", "source_size", F.coalesce(F.least(F.col("cap").cast("double"), F.col("level") * F.col("w")), F.col("cap").cast("double")).alias("target"), "total", block.alias("block"))


def schedule(targets: DataFrame, n_slots: int, few: bool) -> DataFrame:
    """slot, sid and rank (0-based, among the slots of its source)."""
    spark = targets.sparkSession
    points = 1 << POINT_BITS
    share = targets.where("target > 0").withColumn("q", F.floor(F.col("target") / F.col("total") * points).cast("long"))
    # the last span ends with the points, whatever rounding left
    spans = (
        share.withColumn("hi", F.sum("q").over(W.orderBy("sid")))
        .withColumn("lo", F.col("hi") - F.col("q"))
        .withColumn("hi", F.when(F.lead("sid").over(W.orderBy("sid")).isNull(), F.lit(points)).otherwise(F.col("hi")))
        .where("lo < hi")
    )
    shift = POINT_BITS - CELL_BITS
    cells = spans.select("sid", "lo", "hi", F.explode(F.sequence(F.shiftright("lo", shift), F.shiftright(F.col("hi") - 1, shift))).alias("cell"))
    mask = F.lit(points - 1)
    slots = spark.range(n_slots).select(F.col("id").alias("slot"), (F.col("id").bitwiseAND(mask) * GOLDEN).bitwiseAND(mask).alias("u"))
    slots = slots.withColumn("cell", F.shiftright("u", shift))
    drawn = slots.join(F.broadcast(cells) if few else cells, "cell").where("lo <= u and u < hi").select("slot", "sid", F.shiftright("slot", SLOT_CHUNK_BITS).alias("chunk"))
    near = drawn.withColumn("near", F.row_number().over(W.partitionBy("chunk", "sid").orderBy("slot")) - 1)
    counts = drawn.groupBy("sid", "chunk").count()
    before = counts.withColumn("before", F.coalesce(F.sum("count").over(W.partitionBy("sid").orderBy("chunk").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    return near.join(before.drop("count"), ["sid", "chunk"]).select("slot", "sid", (F.col("before") + F.col("near")).alias("rank"))


def _starts(sizes: DataFrame) -> DataFrame:
    """``sizes`` (with sid) plus start: words of its source before the document
    in shuffled order."""
    name = F.md5(F.concat(F.lit(SEED + "-"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))
    rows = sizes.withColumn("h", name).withColumn("h2", F.substring("h", 1, 2)).withColumn("h4", F.substring("h", 1, 4))

    def running(col: str, by: list[str], order: list[str]) -> Column:
        return F.coalesce(F.sum(col).over(W.partitionBy(*by).orderBy(*order).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))

    near = rows.withColumn("near", running("size", ["sid", "h4"], ["h", "doc_id", "size"]))
    fours = rows.groupBy("sid", "h2", "h4").agg(F.sum("size").alias("sum"))
    twos = fours.groupBy("sid", "h2").agg(F.sum("sum").alias("sum")).select("sid", "h2", running("sum", ["sid"], ["h2"]).alias("base"))
    fours = fours.select("sid", "h2", "h4", running("sum", ["sid", "h2"], ["h4"]).alias("within"))
    return (
        near.join(fours.drop("h2"), ["sid", "h4"]).join(twos, ["sid", "h2"])
        .withColumn("start", F.col("base") + F.col("within") + F.col("near"))
        .drop("h", "h2", "h4", "near", "within", "base")
    )


def plan_mix(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, repeats: int = MOST_REPEATS, mark: Column | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(placed, targets, pieces). ``placed`` has a row for each of ``docs``: row (a
    number), doc_id, size, sid, source_size, target, start (in its source) and the
    value of ``mark``. A piece is what one slot takes of one document: slot, sid,
    row, doc_id, start, size, turn, from_word and to_word (within the document)."""
    sizes = staged(document_sizes(docs, mark), "sizes")
    targets = staged(source_targets(sizes, weights, repeats), "targets")
    head = targets.agg(F.count("*"), F.max("total"), F.max("block")).first()
    few, total, block = head[0] <= FEW_SOURCES, head[1] or 0, head[2] or 1
    facts = targets.select(F.col("source").alias("own_source"), "sid", "source_size", "target")
    named = sizes.join(F.broadcast(facts) if few else facts, F.col("source").eqNullSafe(F.col("own_source"))).drop("source", "own_source")
    placed = staged(_starts(named).withColumn("row", F.monotonically_increasing_id()), "placed")
    forget(sizes)
    slots = staged(schedule(targets, -(-total // block), few), "slots")
    ends = slots.groupBy("sid").agg((F.count("*") * block).alias("end"))
    rows = placed.where("size > 0").join(F.broadcast(ends) if few else ends, "sid").withColumn("end", F.least("end", F.col("source_size") * repeats))
    turns = rows.withColumn("turn", F.explode(F.sequence(F.lit(0), F.lit(repeats - 1))))
    cut = turns.withColumn("at", F.col("turn") * F.col("source_size") + F.col("start")).withColumn("to", F.least(F.col("at") + F.col("size"), F.col("end"))).where("at < to")
    parts = cut.withColumn("rank", F.explode(F.sequence(F.expr(f"at div {block}"), F.expr(f"(to - 1) div {block}"))))
    pieces = (
        parts.join(slots, ["sid", "rank"])
        .withColumn("from_word", F.greatest(F.col("rank") * block, F.col("at")) - F.col("at"))
        .withColumn("to_word", F.least((F.col("rank") + 1) * block, F.col("to")) - F.col("at"))
        .select("slot", "sid", "row", "doc_id", "start", "size", "turn", "from_word", "to_word")
    )
    return placed, targets, pieces


def _taken(placed: DataFrame, pieces: DataFrame) -> DataFrame:
    sums = pieces.groupBy("row").agg(F.sum(F.col("to_word") - F.col("from_word")).alias("taken"))
    return placed.join(sums, "row", "left").withColumn("taken", F.coalesce("taken", F.lit(0)).cast("long"))


def words_taken(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, repeats: int = MOST_REPEATS) -> DataFrame:
    """doc_id, size, source_size, target and taken of every row of ``docs``."""
    placed, _, pieces = plan_mix(docs, weights, repeats)
    return _taken(placed, pieces).select("doc_id", "size", "source_size", "target", "taken")


def mixed_documents(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, repeats: int = MOST_REPEATS) -> DataFrame:
    """The rows of ``docs`` as often as the mix takes them, to the nearest whole
    number. The mix takes all of a source's documents equally often but for the
    part of one that its last block cuts, so a source's words stay within half a
    document of what the mix takes. Equal rows are taken equally often."""
    rowmark = F.xxhash64(F.col("source").cast("string"), F.coalesce(F.col("text"), F.lit("")))
    placed, _, pieces = plan_mix(docs, weights, repeats, rowmark)
    own_id, own_mark, times, turn = free_names(docs, "id_", "mark_", "times_", "turn_")
    every = _taken(placed, pieces).where("taken > 0").groupBy(F.col("doc_id").alias(own_id), F.col("mark").alias(own_mark)).agg(F.round(F.sum("taken") / F.sum("size")).cast("int").alias(times))
    joined = docs.join(every.where(F.col(times) > 0), docs["doc_id"].eqNullSafe(F.col(own_id)) & (rowmark == F.col(own_mark)))
    return joined.withColumn(turn, F.explode(F.sequence(F.lit(1), F.col(times)))).select(*[docs[c] for c in docs.columns])
