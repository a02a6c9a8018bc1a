"""Set lane of the codecs: sizes and words from rows (message keys, slot, n_bits), inside the JVM, without building payloads.

A message is named by its key columns; `frame` has one row per message with n_bits, so that messages without members have sizes too.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def set_sizes(members: DataFrame, keys: list[str]) -> DataFrame:
    return members.groupBy(*keys).agg(F.count("*").alias("n_set"))


def bitmap_bytes(n_bits):
    return F.ceil(n_bits / 8).cast("long")


def wah_groups(members: DataFrame, keys: list[str], width: int) -> DataFrame:
    """One row per non-empty full group: its number, members and literal value."""
    g = width - 1
    rows = members.withColumn("grp", F.floor(F.col("slot") / g).cast("long"))
    rows = rows.where(F.col("grp") < F.floor(F.col("n_bits") / g))
    value = F.sum(F.expr(f"shiftleft(1L, cast({g - 1} - slot % {g} as int))")).alias("value")
    return rows.groupBy(*keys, "grp").agg(F.count("*").alias("n"), F.max("n_bits").alias("n_bits"), value)


def wah_words(members: DataFrame, frame: DataFrame, keys: list[str], width: int, plwah: bool = False) -> DataFrame:
    """(keys, n_set, words) of every message. plwah: a literal with one bit right behind a zero fill costs nothing."""
    g = width - 1
    most = (1 << 25) - 1 if plwah else (1 << (width - 2)) - 1
    groups = wah_groups(members, keys, width)
    by = Window.partitionBy(*keys).orderBy("grp")
    one = F.col("n") == g
    before = F.coalesce(F.lag("grp").over(by), F.lit(-1))
    rows = groups.select(*keys, "grp", "n", one.alias("one"), (F.col("grp") - before - 1).alias("gap"), (F.col("grp") - F.row_number().over(by)).alias("island"), F.lag(one).over(by).alias("one_before"))
    starts = F.col("one") & ~(F.coalesce(F.col("one_before"), F.lit(False)) & (F.col("gap") == 0))
    rows = rows.withColumn("ones_run", F.sum(starts.cast("long")).over(by))
    runs = rows.where("one").groupBy(*keys, "ones_run").agg(F.count("*").alias("n")).groupBy(*keys).agg(F.sum(F.ceil(F.col("n") / most)).alias("one_fills"))
    absorbed = (F.col("n") == 1) & (F.col("gap") > 0) if plwah else F.lit(False)
    sums = rows.groupBy(*keys).agg(
        F.sum((~F.col("one") & ~absorbed).cast("long")).alias("literals"),
        F.sum(F.ceil(F.col("gap") / most)).alias("zero_fills"),
        F.max("grp").alias("last"),
    )
    full = F.floor(F.col("n_bits") / g)
    out = frame.join(set_sizes(members, keys), keys, "left").join(sums, keys, "left").join(runs, keys, "left")
    tail = F.ceil((full - 1 - F.coalesce("last", F.lit(-1))) / most)
    words = F.coalesce("literals", F.lit(0)) + F.coalesce("zero_fills", F.lit(0)) + F.coalesce("one_fills", F.lit(0)) + tail + (F.col("n_bits") % g > 0).cast("long")
    return out.select(*keys, "n_bits", F.coalesce("n_set", F.lit(0)).alias("n_set"), words.cast("long").alias("words"))


def wah_word_rows(members: DataFrame, frame: DataFrame, keys: list[str], width: int) -> DataFrame:
    """(keys, word_no, word_hex): the words themselves. Runs longer than a counter holds are split."""
    g, digits = width - 1, width // 4
    most = (1 << (width - 2)) - 1
    groups = wah_groups(members, keys, width)
    by = Window.partitionBy(*keys).orderBy("grp")
    one = F.col("n") == g
    full = F.floor(F.col("n_bits") / g)
    rows = groups.withColumns({"one": one, "prev": F.coalesce(F.lag("grp").over(by), F.lit(-1)), "prev_one": F.coalesce(F.lag(one).over(by), F.lit(False))})
    rows = rows.withColumn("run", F.sum((F.col("one") & ~(F.col("prev_one") & (F.col("prev") == F.col("grp") - 1))).cast("long")).over(by))
    literal = rows.where(~F.col("one")).select(*keys, F.col("grp").alias("at"), F.lit(2).alias("kind"), F.lit(1).cast("long").alias("n"), "value")
    ones = rows.where("one").groupBy(*keys, "run").agg(F.min("grp").alias("at"), F.count("*").alias("n")).select(*keys, "at", F.lit(1).alias("kind"), "n", F.lit(0).cast("long").alias("value"))
    gaps = rows.where(F.col("grp") > F.col("prev") + 1).select(*keys, (F.col("prev") + 1).alias("at"), F.lit(0).alias("kind"), (F.col("grp") - F.col("prev") - 1).alias("n"), F.lit(0).cast("long").alias("value"))
    last = frame.join(groups.groupBy(*keys).agg(F.max("grp").alias("last")), keys, "left").withColumn("at", F.coalesce("last", F.lit(-1)) + 1)
    tails = last.where(F.col("at") < full).select(*keys, "at", F.lit(0).alias("kind"), (full - F.col("at")).cast("long").alias("n"), F.lit(0).cast("long").alias("value"))
    part = members.where(F.floor(F.col("slot") / g) == full).groupBy(*keys).agg(F.sum(F.expr(f"shiftleft(1L, cast(n_bits % {g} - 1 - slot % {g} as int))")).alias("value"))
    active = frame.where(F.col("n_bits") % g > 0).join(part, keys, "left").select(*keys, full.cast("long").alias("at"), F.lit(2).alias("kind"), F.lit(1).cast("long").alias("n"), F.coalesce("value", F.lit(0)).cast("long").alias("value"))
    fills = gaps.unionByName(tails).unionByName(ones)
    split = fills.withColumn("i", F.explode(F.sequence(F.lit(0), (F.ceil(F.col("n") / most) - 1).cast("int"))))
    split = split.select(*keys, "at", "kind", F.least(F.lit(most).cast("long"), F.col("n") - F.col("i") * F.lit(most)).alias("n"), "value", "i")
    every = split.unionByName(literal.unionByName(active).withColumn("i", F.lit(0)))
    low = width - 4
    head = F.lit(8) + 4 * F.col("kind") + F.shiftright("n", low)
    fill = F.concat(F.hex(head), F.lpad(F.hex(F.col("n").bitwiseAND(F.lit((1 << low) - 1))), digits - 1, "0"))
    word = F.when(F.col("kind") == 2, F.lpad(F.hex("value"), digits, "0")).otherwise(fill)
    number = F.row_number().over(Window.partitionBy(*keys).orderBy("at", "i"))
    return every.select(*keys, number.cast("long").alias("word_no"), F.lower(word).alias("word_hex"))


def rle_runs(members: DataFrame, frame: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, n_set, runs): maximal runs of equal bits, counted from a perhaps empty run of zeros."""
    by = Window.partitionBy(*keys).orderBy("slot")
    starts = members.withColumn("new", (F.coalesce(F.lag("slot").over(by), F.lit(-2)) != F.col("slot") - 1).cast("long"))
    sums = starts.groupBy(*keys).agg(F.sum("new").alias("ones"), F.max("slot").alias("last"), F.count("*").alias("n_set"))
    out = frame.join(sums, keys, "left")
    # each run of ones has a run of zeros before it (the first may be empty); zeros behind the last are one more
    runs = F.coalesce(2 * F.col("ones") + (F.col("last") < F.col("n_bits") - 1).cast("long"), F.lit(1))
    return out.select(*keys, "n_bits", F.coalesce("n_set", F.lit(0)).alias("n_set"), runs.alias("runs"))


def varint_bytes(members: DataFrame, frame: DataFrame, keys: list[str]) -> DataFrame:
    by = Window.partitionBy(*keys).orderBy("slot")
    gap = F.col("slot") - F.coalesce(F.lag("slot").over(by), F.lit(0))
    size = F.when(gap < 1 << 7, 1).when(gap < 1 << 14, 2).when(gap < 1 << 21, 3).when(gap < 1 << 28, 4).otherwise(5)
    sums = members.select(*keys, size.cast("long").alias("b")).groupBy(*keys).agg(F.sum("b").alias("bytes"), F.count("*").alias("n_set"))
    return frame.join(sums, keys, "left").select(*keys, "n_bits", F.coalesce("n_set", F.lit(0)).alias("n_set"), F.coalesce("bytes", F.lit(0)).alias("bytes"))


def sized(members: DataFrame, frame: DataFrame, keys: list[str], codec: str) -> DataFrame:
    """(keys, n_bits, n_set, bytes) of every message under a codec of the set lane."""
    if codec in ("bitmap", "sparse"):
        out = frame.join(set_sizes(members, keys), keys, "left").withColumn("n_set", F.coalesce("n_set", F.lit(0)))
        return out.select(*keys, "n_bits", "n_set", (bitmap_bytes(F.col("n_bits")) if codec == "bitmap" else F.col("n_set") * 8).alias("bytes"))
    if codec == "varint":
        return varint_bytes(members, frame, keys)
    if codec == "rle":
        out = rle_runs(members, frame, keys)
        return out.select(*keys, "n_bits", "n_set", (F.col("runs") * 4).alias("bytes"))
    width = {"wah": 32, "plwah": 32, "wah8": 8, "wah16": 16, "wah64": 64}[codec]
    out = wah_words(members, frame, keys, width, codec == "plwah")
    return out.select(*keys, "n_bits", "n_set", (F.col("words") * (width // 8)).alias("bytes"))
