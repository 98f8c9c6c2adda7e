"""Mixing sources to target weights by Pareto order sampling, in DataFrame functions only.

A document's expected number of copies is its importance times a level of its source, at most
``max_copies``; the level is such that the expected words of the source are its target.  The whole
part is given for certain.  The fraction is the document's inclusion probability in the draw:
documents are ranked by their random odds divided by their inclusion odds, and the first in that
order are taken until the words still due are reached.

Nothing of the size of a source is brought together: levels come from sums by source and
importance, and the cut of a source from sums over rank cells, 256 to a source, the one that holds
the cut being cut into 256 again until it is small.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from levelgraph.runtime import discard, materialize

WEIGHTS = (5, 2, 1)
SHARE = 1.5
MAX_COPIES = 2
FAN = 256
# rows of the cell that is ordered row by row, at most, unless they tie
CELL_ROWS = 4096
UNIT = 1024.0
SEED = 11
WORD = r"[^\x20\x09-\x0D]+"


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, max_copies: int = MAX_COPIES) -> DataFrame:
    """Target of each source from ``source, source_size``: shares by weight, filled up to the caps.

    Sources in code-point order (null last) take the weights in turn.  A source stops at
    ``max_copies`` times its size and the excess goes to the others by weight.  The level at which
    that ends comes from running sums over sources ordered by cap / weight.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    place = F.row_number().over(order) - 1
    w = F.element_at(F.array(*map(F.lit, weights)), (place % len(weights) + 1).cast("int")).cast("double")
    s = sizes.withColumn("weight", w).withColumn("cap", (F.col("source_size") * max_copies).cast("double"))
    s = s.withColumn("ratio", F.col("cap") / F.col("weight"))
    up = Window.orderBy("ratio", F.col("source").asc_nulls_last())
    before, rest = up.rowsBetween(Window.unboundedPreceding, -1), up.rowsBetween(0, Window.unboundedFollowing)
    whole = Window.partitionBy()
    s = s.withColumns(
        {
            "budget": F.sum("source_size").over(whole) * F.lit(float(share)),
            "filled": F.coalesce(F.sum("cap").over(before), F.lit(0.0)),
            "open": F.sum("weight").over(rest),
        }
    )
    # the level if every source before this one stops at its cap: the first that the source's own cap reaches
    s = s.withColumn("level", (F.col("budget") - F.col("filled")) / F.col("open"))
    level = F.min(F.when(F.col("level") <= F.col("ratio"), F.struct("ratio", "level"))).over(whole)["level"]
    s = s.withColumn("at", level)
    return s.select("source", "source_size", F.when(F.col("at").isNull() | (F.col("at") >= F.col("ratio")), F.col("cap")).otherwise(F.col("at") * F.col("weight")).alias("target"))


def uniform(seed: int, *keys: Column | str) -> Column:
    """A number in (0, 1) that depends on the seed and the keys alone: 52 bits of an md5, the same in any engine."""
    named = F.concat_ws(":", F.lit(str(seed)), *[F.col(k).cast("string") if isinstance(k, str) else k.cast("string") for k in keys])
    return (F.conv(F.substring(F.md5(named), 1, 13), 16, 10).cast("long") + F.lit(0.5)) / F.lit(float(1 << 52))


def _key() -> Column:
    return F.struct(F.col("source").isNull().alias("null"), F.coalesce(F.col("source").cast("string"), F.lit("")).alias("name"))


def _quoted(name: str) -> Column:
    return F.col("`" + name.replace("`", "``") + "`")


def default_importance(size: Column) -> Column:
    """Longer documents are likelier, by the square root of their size."""
    return F.sqrt(size + 1)


def _sized(docs: DataFrame, size: Column | None, importance: Column | None, *more: Column) -> DataFrame:
    """``_id, _size, _tilt, _key`` of each row and what ``more`` adds; the tilt is the importance in whole units."""
    number = word_count(F.col("text")) if size is None else size.cast("long")
    tilt = F.col("_weight") if importance is not None else default_importance(F.col("_size"))
    first = docs.select(*more, F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("_id"), number.alias("_size"), _key().alias("_key"), *([importance.cast("double").alias("_weight")] if importance is not None else []))
    names = [x for x in first.columns if x not in ("_id", "_size", "_key", "_weight")]
    units = F.greatest(F.floor(F.coalesce(tilt, F.lit(0.0)) * UNIT), F.lit(1)).cast("long")
    return first.select(*names, "_id", "_size", "_key", units.alias("_tilt"))


def source_levels(rows: DataFrame, targets: DataFrame, max_copies: int) -> DataFrame:
    """``_key, source_size, target, level``: ``sum(size * least(max_copies, level * tilt))`` is the target.

    Documents at the cap are taken out and their words off the target, until no other reaches it;
    sums are exact, so the level does not depend on the order of rows."""
    heap = materialize(rows.where("_size > 0").groupBy("_key", "_tilt").agg(F.sum(F.col("_size").cast("decimal(38,0)")).alias("words")), "mix_weights")
    state = targets.withColumns({"level": F.lit(0.0), "held": F.lit(-1).cast("decimal(38,0)")})
    while True:
        capped = F.col("level") * F.col("_tilt") >= max_copies
        part = heap.join(state, "_key").groupBy("_key").agg(
            F.first("source_size").alias("source_size"), F.first("target").alias("target"), F.first("level").alias("was"), F.first("held").alias("before"),
            F.coalesce(F.sum(F.when(capped, F.col("words"))), F.lit(0)).cast("decimal(38,0)").alias("held"),
            F.sum(F.when(~capped, F.col("words") * F.col("_tilt"))).cast("double").alias("open"),
        )
        full = F.col("target") >= max_copies * F.col("source_size")
        level = F.when(full, F.lit(1e300)).when(F.col("open").isNull(), F.col("was")).otherwise((F.col("target") - max_copies * F.col("held").cast("double")) / F.col("open"))
        new = materialize(part.select("_key", "source_size", "target", level.alias("level"), "held", (F.col("held") != F.col("before")).alias("moved")), "mix_levels")
        more = not new.where(F.col("moved") & (F.col("level") < 1e300)).isEmpty()
        discard(state)
        state = new.drop("moved")
        state._levelgraph_path = new._levelgraph_path
        if not more:
            discard(heap)
            return state.drop("held")


def _drawn(rows: DataFrame, plan: DataFrame, max_copies: int, seed: int) -> DataFrame:
    """Adds ``_whole``, the certain copies, and ``_turn``, the place in the source's order in (0, 1); null where nothing is left to chance.

    The turn is the random odds over the inclusion odds, as a number in (0, 1); ties go by id and size."""
    u = uniform(seed, "_id", "_size")
    out = rows.join(plan, "_key").withColumn("_due", F.least(F.col("level") * F.col("_tilt"), F.lit(float(max_copies))))
    out = out.withColumn("_whole", F.floor("_due").cast("long"))
    chance = F.least(F.greatest(F.col("_due") - F.col("_whole"), F.lit(1e-9)), F.lit(1 - 1e-9))
    odds = (u / (1 - u)) / (chance / (1 - chance))
    return out.withColumn("_turn", F.when(F.col("_due") > F.col("_whole"), odds / (1 + odds))).drop("_due")


def draw_plan(rows: DataFrame, weights: tuple[int, ...], share: float, max_copies: int, seed: int, cell_rows: int = CELL_ROWS) -> DataFrame:
    """One row per source: ``_key, source_size, target, level, stop``; rows whose turn is before ``stop`` are drawn.

    Of ``rows`` (``_id, _size, _tilt, _key``) only sums are shuffled, and the rows of one small cell per source."""
    sums = rows.groupBy("_key").agg(F.sum("_size").alias("source_size"))
    targets = source_targets(sums.select(F.when(~F.col("_key.null"), F.col("_key.name")).alias("source"), "source_size"), weights, share, max_copies)
    targets = materialize(targets.select(_key().alias("_key"), "source_size", "target"), "mix_targets")
    levels = source_levels(rows, targets, max_copies)
    # sources without a word have no level; nothing of them is taken whatever it is
    levels = targets.join(levels.select("_key", "level"), "_key", "left").withColumn("level", F.coalesce("level", F.lit(0.0)))
    levels = materialize(levels, "mix_levels")
    ranked = _drawn(rows, levels, max_copies, seed)
    due = ranked.groupBy("_key").agg(F.sum(F.col("_whole") * F.col("_size")).alias("certain"))
    state = levels.join(due, "_key").select("_key", (F.col("target") - F.col("certain")).alias("due"), F.lit(0).cast("long").alias("cell"), F.lit(0).cast("long").alias("before"))
    state = materialize(state, "mix_cells")
    chosen = ranked.where("_turn is not null").select("_key", "_id", "_size", "_turn")
    cells = 1
    while True:
        cells *= FAN
        inner = chosen.join(state.withColumnRenamed("cell", "outer"), "_key").withColumn("cell", F.floor(F.col("_turn") * cells).cast("long")).where(F.expr(f"cell div {FAN} = outer"))
        part = inner.groupBy("_key", "cell").agg(F.sum("_size").alias("words"), F.count("*").alias("n"), F.first("due").alias("due"), F.first("before").alias("base"))
        run = Window.partitionBy("_key").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)  # at most FAN rows a source
        part = part.withColumn("before", F.col("base") + F.coalesce(F.sum("words").over(run), F.lit(0)))
        # the first cell in which the words due run out; sources whose words all fit have none
        new = part.where(F.col("before") + F.col("words") > F.col("due")).groupBy("_key").agg(F.min(F.struct("cell", "before", "due", "n")).alias("c"))
        new = materialize(new.select("_key", "c.due", "c.cell", "c.before", "c.n"), "mix_cells")
        most = new.agg(F.max("n").alias("n")).first()["n"] or 0
        discard(state)
        state = new
        if most <= cell_rows or cells >= FAN**6:
            break
    rest = chosen.join(state.drop("n"), "_key").where(F.floor(F.col("_turn") * cells).cast("long") == F.col("cell"))
    ties = rest.groupBy("_key", "_turn", "_id", "_size", "due", "before").agg((F.count("*") * F.col("_size")).alias("words"))
    order = Window.partitionBy("_key").orderBy("_turn", "_id", "_size").rowsBetween(Window.unboundedPreceding, -1)
    late = ties.withColumn("ahead", F.col("before") + F.coalesce(F.sum("words").over(order), F.lit(0))).where(F.col("ahead") + F.col("words") / 2 > F.col("due"))
    place = lambda turn: F.struct(turn.cast("double").alias("turn"), F.lit(-(1 << 63)).cast("long").alias("_id"), F.lit(-1).cast("long").alias("_size"))
    stop = late.groupBy("_key").agg(F.min(F.struct(F.col("_turn").alias("turn"), "_id", "_size")).alias("late"))
    stops = state.join(stop, "_key", "left").select("_key", F.coalesce("late", place((F.col("cell") + 1) / cells)).alias("stop"))
    out = materialize(levels.join(stops, "_key", "left").withColumn("stop", F.coalesce("stop", place(F.lit(2.0)))), "mix_draw")
    for table in (state, levels, targets):
        discard(table)
    return out


def _copies(rows: DataFrame, plan: DataFrame, max_copies: int, seed: int) -> DataFrame:
    out = _drawn(rows, plan, max_copies, seed)
    drawn = F.coalesce(F.struct(F.col("_turn").alias("turn"), "_id", "_size") < F.col("stop"), F.lit(False)) & F.col("_turn").isNotNull()
    return out.withColumn("_copies", F.least(F.col("_whole") + drawn.cast("long"), F.lit(max_copies)))


def mix(
    docs: DataFrame,
    size: Column | None = None,
    weights: tuple[int, ...] = WEIGHTS,
    share: float = SHARE,
    max_copies: int = MAX_COPIES,
    importance: Column | None = None,
    seed: int = SEED,
    cell_rows: int = CELL_ROWS,
) -> DataFrame:
    """Copies of each row of ``docs`` (``doc_id``, ``text``, ``source``) in the mix.

    Returns ``doc_id, source, size, source_size, target, copies, taken``.  ``importance`` sets how
    the expected copies of documents of one source compare (by default the square root of their
    size; a literal gives all the same).  Null texts and texts without words have size 0 and null
    importances count as the least; a null source is a source of its own; null ids count as one
    id.  Rows that repeat an id and a size get the same draw, and each counts.  An empty table
    gives an empty result; other columns are ignored, whatever their names.
    """
    rows = _sized(docs, size, importance, F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"))
    rows = materialize(rows, "mix_sizes")
    plan = draw_plan(rows, weights, share, max_copies, seed, cell_rows)
    out = _copies(rows, plan, max_copies, seed)
    return out.select("doc_id", "source", F.col("_size").alias("size"), "source_size", "target", F.col("_copies").alias("copies"), (F.col("_copies") * F.col("_size")).alias("taken"))


def mixed_documents(
    docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, max_copies: int = MAX_COPIES, importance: Column | None = None, seed: int = SEED, cell_rows: int = CELL_ROWS
) -> DataFrame:
    """The mix itself: every row of ``docs`` as often as it is drawn, with its own columns.

    The draw is decided from one small row per source, so texts stay where they are read.  Nulls,
    ties, repeated rows and empty tables are treated as in :func:`mix`."""
    rows = materialize(_sized(docs, None, importance), "mix_sizes")
    plan = draw_plan(rows, weights, share, max_copies, seed, cell_rows)
    discard(rows)
    body = F.struct(*[_quoted(c) for c in docs.columns]).alias("_row")
    drawn = _copies(_sized(docs, None, importance, body), plan, max_copies, seed).where("_copies > 0")
    return drawn.select("_row", F.explode(F.sequence(F.lit(1), F.col("_copies").cast("int"))).alias("_copy")).select("_row.*")


def op2_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source")
    return mix(docs).select("doc_id", "size", "source_size", "target", "taken")
