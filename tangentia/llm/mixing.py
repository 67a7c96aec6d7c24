"""Mixing sources to target weights as a time-varying curriculum (all DataFrame functions).

Each source has a share of the words to train on (its target) and a weight that falls, rises or stays level over
training. Time is the share of all words read so far, one clock for all sources: at each time the rates at which
sources give words add up to the whole, and none is negative. Integrated, a source's rate says how many words it
has given by time t; inverted, at which time its x-th word is read. Documents are laid out along their source in the
order of a hash, so a document owns an interval of words, once for each pass over the source. What of it is read by time
1 is what the mix takes, its start gives the training position of the pass, and documents are range-sorted by position.

The running sum along a source goes in two steps, slices of the hash range first and rows within a slice
then, so a source with a third of all rows is spread over all tasks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tangentia.session import materialise

WORD = r"[^\x20\x09-\x0D]+"
SLICE_DIGITS = 3  # hex digits of the hash that name a slice: 4,096 slices for each source


def document_size(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


SLOPES = (-0.5, 0.5, 0.0)  # of the sources in turn: over training, the weight moves by this share below and above its mean


def source_targets(sources: DataFrame, weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, most: float = 2.0, slopes: tuple[float, ...] = SLOPES) -> DataFrame:
    """(source, source_size, target, slope) of (source, source_size) rows, one for each source.

    Sources by code point, null last, get the weights in turn. ``share`` times all words are dealt by weight;
    no target goes beyond ``most`` times its source's size, and what is above goes to the rest by weight.
    In the order of the level at which they fill, sources fill one after another: a source is full if the
    level reached when all before it are full would fill it too. The table has a row for each source only.

    At time t a source's rate is its target times 1 + slope (2t - 1). Slopes, each between -1/2 and 1/2, are dealt in turn too and
    then moved by their mean over targets, so that the rates of all sources always add up to all targets.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    if not all(abs(x) <= 0.5 for x in slopes):
        raise ValueError("slopes must lie between -1/2 and 1/2, or rates could fall below nothing")
    dealt = lambda values: F.element_at(F.array(*[F.lit(x) for x in values]), ((F.row_number().over(by_name) - 1) % len(values)) + 1)
    t = sources.withColumns({"weight": dealt(weights), "slope": dealt(slopes)})
    t = t.withColumn("cap", most * F.col("source_size").cast("double"))
    by_level = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    before, onward, everything = by_level.rowsBetween(Window.unboundedPreceding, -1), by_level.rowsBetween(0, Window.unboundedFollowing), Window.partitionBy()
    t = t.withColumn("level", (share * F.sum("source_size").over(everything) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(onward))
    t = t.withColumn("full", F.col("level") * F.col("weight") >= F.col("cap"))
    last = F.min(F.when(~F.col("full"), F.struct(F.col("cap") / F.col("weight"), F.col("level").alias("l")))).over(everything)["l"]
    t = t.withColumn("target", F.when(F.col("full"), F.col("cap")).otherwise(F.coalesce(last, F.lit(0.0)) * F.col("weight")))
    goal = F.round("target")
    mean = F.sum(goal * F.col("slope")).over(everything) / F.greatest(F.sum(goal).over(everything), F.lit(1.0))
    return t.select("source", "source_size", "target", (F.col("slope") - mean).alias("slope"))


def lay_out(docs: DataFrame, weights=(3, 1, 2), share: float = 1.5, most: float = 2.0, seed: int = 0, slopes=SLOPES, carry: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, source, size, source_size, target, slope, start, digest, row): ``start`` is the word of its source at which a document begins.

    ``row`` has the columns named in ``carry``; with none, sizes are written first, so that texts are read once.
    """
    hashed = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("doc_id").cast("string")))
    name = F.when(F.col("source").isNull(), F.lit("")).otherwise(F.concat(F.lit("="), F.col("source").cast("string")))
    row = F.struct(*carry) if carry else F.struct(F.lit(0).alias("none"))
    rows = docs.select("doc_id", "source", name.alias("name"), document_size(F.col("text")).alias("size"), hashed.alias("digest"), row.alias("row"))
    rows = rows if carry else materialise(rows, "sizes")
    rows = rows.withColumn("slice", F.substring("digest", 1, SLICE_DIGITS))
    slices = rows.groupBy("name", "slice").agg(F.sum("size").alias("slice_size"))
    sources = slices.groupBy("name").agg(F.sum("slice_size").alias("source_size")).withColumn("source", F.when(F.col("name") != "", F.substring("name", 2, 1 << 30)))
    targets = source_targets(sources, weights, share, most, slopes)
    targets = targets.withColumn("name", F.when(F.col("source").isNull(), F.lit("")).otherwise(F.concat(F.lit("="), F.col("source")))).drop("source")
    along = Window.partitionBy("name").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    slices = slices.withColumn("slice_start", F.coalesce(F.sum("slice_size").over(along), F.lit(0))).drop("slice_size").join(targets, "name")
    within = Window.partitionBy("name", "slice").orderBy("digest", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    placed = rows.withColumn("before", F.coalesce(F.sum("size").over(within), F.lit(0))).join(slices, ["name", "slice"])
    return placed.select("doc_id", "source", "size", "source_size", "target", "slope", (F.col("slice_start") + F.col("before")).alias("start"), "digest", "row")


def words_given(t: Column, goal: Column, slope: Column) -> Column:
    """How many of its ``goal`` words a source has given by time t: the integral of its rate."""
    return goal * ((1 - slope) * t + slope * t * t)


def training_time(word: Column, goal: Column, slope: Column) -> Column:
    """The time at which a source's ``word`` is read: the inverse of ``words_given``, in a form that does not lose digits at small slopes."""
    fraction = word / goal
    root = 2 * fraction / ((1 - slope) + F.sqrt(F.greatest((1 - slope) * (1 - slope) + 4 * slope * fraction, F.lit(0.0))))
    return F.when(fraction > 0, F.least(root, F.lit(1.0))).otherwise(F.lit(0.0))


def schedule(laid: DataFrame, most: float = 2.0) -> DataFrame:
    """``laid`` with ``passes``: an array of (epoch, taken, position), one for each pass that begins before time 1; taken is what of it is read by then."""
    goal = F.round("target").cast("long")
    turns = F.sequence(F.lit(0), F.lit(int(most) + (most > int(most)) - 1))
    # a pass begins before time 1 just if its first word is below the goal, of which all is given at time 1
    begins = lambda k: F.col("start") + k * F.col("source_size")
    turn = lambda k: F.struct(
        k.alias("epoch"),
        F.least(F.col("size"), goal - begins(k)).alias("taken"),
        training_time(begins(k).cast("double"), goal.cast("double"), F.col("slope")).alias("position"),
    )
    return laid.withColumn("passes", F.transform(F.filter(turns, lambda k: (begins(k) < goal) & (F.col("size") > 0)), turn))


def mix_report(docs: DataFrame, weights=(3, 1, 2), share: float = 1.5, most: float = 2.0, seed: int = 0, slopes=SLOPES) -> DataFrame:
    """(doc_id, source, size, source_size, target, taken, passes, position, last_position) of each row, in training order.

    taken: words read of it in all passes; position, last_position: the times in [0, 1] at which its first and last pass begin.
    Null texts have size 0; what is never read has no passes, takes 0, has null positions and comes first; null sources are
    one source; repeated rows lie one after another; rows with no doc_id are placed as all others; other columns are
    ignored; an empty table gives no rows.
    """
    rows = schedule(lay_out(docs, weights, share, most, seed, slopes), most)
    taken = F.aggregate("passes", F.lit(0).cast("long"), lambda total, p: total + p["taken"])
    rows = rows.select("doc_id", "source", "size", "source_size", "target", taken.alias("taken"), F.size("passes").alias("passes"), F.get("passes", F.lit(0))["position"].alias("position"), F.try_element_at("passes", F.lit(-1))["position"].alias("last_position"), "digest")
    return rows.repartitionByRange("position", "digest").sortWithinPartitions("position", "digest").drop("digest")


def curriculum(docs: DataFrame, weights=(3, 1, 2), share: float = 1.5, most: float = 2.0, seed: int = 0, slopes=SLOPES) -> DataFrame:
    """The mix in training order: ``docs``' columns, epoch, taken (words of this pass) and position in [0, 1], a row for each pass over a document.

    Documents of no words (null texts too), or never reached, have no row. Columns of ``docs`` that are named like the new
    ones are replaced; an empty table gives no rows.
    """
    columns = [c for c in docs.columns if c not in ("epoch", "taken", "position")]
    rows = schedule(lay_out(docs, weights, share, most, seed, slopes, tuple(columns)), most)
    rows = rows.select("row", "digest", F.explode("passes").alias("pass")).select("row", "digest", "pass.*")
    rows = rows.repartitionByRange("position", "digest").sortWithinPartitions("position", "digest")
    return rows.select("row.*", "epoch", "taken", "position")
