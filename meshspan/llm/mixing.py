"""Mixing sources to target weights by weighted sampling without replacement.

Targets are the shares of all words by weight, stopped at a multiple of each source's size; what is
cut off goes to the others by weight. A source gives whole epochs first; the rest is a fractional
epoch in the order of exponential keys: a document of weight w draws -ln(u) / w from a hash of its
id, and the smallest keys come first until the word budget is met.

The order within a source is never sorted as a whole: keys are mapped to 4,096 ordered bins, word
counts are summed per source and bin, and only the bin in which the budget ends is ordered by row.
A source that holds most rows costs no more than the others.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from meshspan.llm.common import WORD_PATTERN, stored

_BINS = 4096


def word_count(text: Column) -> Column:
    """Words of a text as a long; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD_PATTERN)), F.lit(0)).cast("long")


def text_weight(text: Column) -> Column:
    """Default quality weight between 0.1 and 1.1: the share of ASCII letters, digits excluded,
    and non-ASCII characters among a text's characters without white space, plus 0.1."""
    bare = F.length(F.regexp_replace(text, r"[\x00-\x40\x5B-\x60\x7B-\x7F]+", ""))
    full = F.length(F.regexp_replace(text, r"[\x00-\x20]+", ""))
    return F.when(full > 0, bare / full + 0.1).otherwise(F.lit(0.1))


def targets(sizes: list[tuple[str | None, int]], cycle: tuple[float, ...] = (1, 2, 3), most: float = 3.0) -> dict[str | None, float]:
    """Target words of each source; ``sizes`` in any order. Weights repeat ``cycle`` over the sources
    by code point, null last; no target passes ``most`` times its source's size."""
    order = sorted(sizes, key=lambda x: (x[0] is None, x[0] or ""))
    weight = {name: cycle[i % len(cycle)] for i, (name, _) in enumerate(order)}
    limit = {name: most * size for name, size in order}
    total = float(sum(size for _, size in order))
    out: dict[str | None, float] = {}
    open_ = [name for name, _ in order]
    while open_:
        rest, share = total - sum(out.values()), sum(weight[n] for n in open_)
        full = [n for n in open_ if rest * weight[n] / share >= limit[n]]
        if not full:
            out |= {n: rest * weight[n] / share for n in open_}
            break
        out |= {n: limit[n] for n in full}
        open_ = [n for n in open_ if n not in out]
    return out


def mixed(
    docs: DataFrame, seed: int = 7, weight: Column | None = None, cycle: tuple[float, ...] = (1, 2, 3), most: float = 3.0,
    max_sources: int = 100_000,
) -> DataFrame:
    """Mix ``docs(doc_id, text, source)``: all columns of ``docs``, plus size, source_size, target and taken (words
    the mix takes of the row, repeats counted), which replace columns of these names; :func:`mixture` keeps any.
    Other columns may not begin with an underscore.

    ``weight``: quality weight column (null or below 0.001 counts as 0.001), default :func:`text_weight`.
    The row in which a budget ends gives its first words only, so that a source's taken words equal its
    target rounded down. Null sources form one source, weighed last; empty texts take nothing; equal
    keys go by doc_id, nulls first, then by a hash of the text; an empty table gives no rows. The
    number of distinct sources is bounded by ``max_sources`` (an error beyond), since their sizes pass
    through the driver.
    """
    spark = docs.sparkSession
    keep = [c for c in docs.columns if c not in ("size", "source_size", "target", "taken")]
    draw = (F.pmod(F.xxhash64(F.lit(seed), F.col("doc_id")), F.lit(1 << 52)) + 0.5) / float(1 << 52)
    weigh = F.greatest(F.coalesce(weight if weight is not None else text_weight(F.col("text")), F.lit(0.001)).cast("double"), F.lit(0.001))
    rows = stored(
        docs.select(*keep, word_count(F.col("text")).alias("size"), (-F.log(draw) / weigh).alias("_key"), F.xxhash64("text").alias("_tie")),
        "rows",
    ).withColumn("_bin", F.floor((1 - F.exp(-F.col("_key"))) * _BINS).cast("int"))
    bins = rows.groupBy("source", "_bin").agg(F.sum("size").alias("words"))
    by_source = rows.groupBy("source").agg(F.sum("size").alias("words")).limit(max_sources + 1).collect()
    if len(by_source) > max_sources:
        raise ValueError(f"over {max_sources} sources")
    goal = targets([(r["source"], r["words"]) for r in by_source], cycle, most)
    plan = []
    for r in by_source:
        size, target = r["words"], goal[r["source"]]
        epochs = int(target // size) if size else 0
        plan.append((r["source"], int(size), float(target), epochs, int(target - epochs * size)))
    plan = spark.createDataFrame(plan, "source string, source_size long, target double, _epochs int, _rest long")
    before = Window.partitionBy("source").orderBy("_bin").rowsBetween(Window.unboundedPreceding, -1)
    edges = (  # at most one row per source: the bin in which its fractional epoch ends
        bins.withColumn("_before", F.coalesce(F.sum("words").over(before), F.lit(0)))
        .join(F.broadcast(plan.select(F.col("source").alias("_s"), "_rest")), F.col("source").eqNullSafe(F.col("_s")))
        .where("_before <= _rest and _before + words > _rest")
        .select("_s", F.col("_bin").alias("_edge"), "_before")
    )
    plan = plan.alias("p").join(F.broadcast(edges), F.col("p.source").eqNullSafe(F.col("_s")), "left").select(
        F.col("p.source").alias("_source"), "source_size", "target", "_epochs", "_rest", "_edge", "_before"
    )
    rows = rows.join(F.broadcast(plan), rows.source.eqNullSafe(F.col("_source")))
    inside = F.col("_bin") == F.col("_edge")
    order = Window.partitionBy("source", "_bin").orderBy("_key", F.col("doc_id").asc_nulls_first(), "_tie", "size").rowsBetween(Window.unboundedPreceding, -1)
    cut = rows.where(inside).withColumn("_ahead", F.coalesce(F.sum("size").over(order), F.lit(0)) + F.col("_before"))
    cut = cut.withColumn("_part", F.greatest(F.lit(0), F.least("size", F.col("_rest") - F.col("_ahead")))).drop("_ahead")
    whole = rows.where(~F.coalesce(inside, F.lit(False))).withColumn(
        "_part", F.when(F.col("_edge").isNull() | (F.col("_bin") < F.col("_edge")), F.when(F.col("_edge").isNull() & (F.col("_rest") == 0), F.lit(0)).otherwise(F.col("size"))).otherwise(F.lit(0))
    )
    both = whole.unionByName(cut)
    return both.select(*keep, "size", "source_size", "target", (F.col("_epochs") * F.col("size") + F.col("_part")).cast("long").alias("taken"))


def mixture(docs: DataFrame, **settings) -> DataFrame:
    """The rows of :func:`repeated_texts` of the mix of ``docs``, with all columns of ``docs`` whatever their names;
    ``settings`` are those of :func:`mixed`."""
    used = [c for c in docs.columns if c in ("doc_id", "text", "source", "n_chars")]
    others = [c for c in docs.columns if c not in used]
    rows = docs.select(*used, F.struct(*[F.col(f"`{c}`") for c in others]).alias("others")) if others else docs
    mix = repeated_texts(mixed(rows, **settings))
    return mix.select(*[F.col(c) if c in used else F.col("others").getField(c).alias(c) for c in docs.columns])


def repeated_texts(mix: DataFrame) -> DataFrame:
    """The mix as rows: each document once per whole epoch, then its first words if it ends a budget.
    Columns of ``mix`` without size, source_size, target and taken, n_chars of cut texts their new length;
    documents of no words are left out."""
    columns = [c for c in mix.columns if c not in ("size", "source_size", "target", "taken")]
    length = F.when(F.col("_copy") == F.col("text"), F.col("n_chars")).otherwise(F.length("_copy").cast(mix.schema["n_chars"].dataType)) if "n_chars" in columns else None
    whole = F.floor(F.col("taken") / F.col("size")).cast("int")
    rest = (F.col("taken") - whole * F.col("size")).cast("int")
    words = F.regexp_extract_all(F.col("text"), F.lit(r"[\x20\x09-\x0D]*" + WORD_PATTERN), F.lit(0))
    head = F.array_join(F.slice(words, F.lit(1), rest), "")
    parts = F.concat(F.array_repeat(F.col("text"), whole), F.when(rest > 0, F.array(head)).otherwise(F.array().cast("array<string>")))
    changed = {"text": F.col("_copy").alias("text")} | ({"n_chars": length.alias("n_chars")} if length is not None else {})
    return mix.where("taken > 0").withColumn("_copy", F.explode(parts)).select(*[changed.get(c, F.col(c)) for c in columns])
