"""Mixing sources to target weights by hash-random order, distributed prefix sums and exact cuts.

Declarative throughout: a document's random key is a hash of its id, the key's leading bits range-split each source
into a fixed number of ordered slices, slice sums give each slice its starting offset, and a running sum inside the slice
gives each document its place. A source of any size is therefore spread over all its slices.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from floorwalk.llm.runtime import guarded, materialize

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (5, 2, 1)
MAX_EPOCHS = 3
SLICES = 4096


def target_table(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """(source, source_size) -> + target: shares of the whole by weight, none above max_epochs times its source.

    Sources fill up in order of size over weight, so the level at which the rest shares is found from prefix sums of
    one small table (a row per source) instead of rounds.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    cycle = F.array(*[F.lit(w) for w in weights])
    table = sizes.withColumn("weight", F.element_at(cycle, ((F.row_number().over(by_name) - 1) % len(weights) + 1).cast("int")))
    table = table.withColumn("cap", F.col("source_size") * max_epochs)
    by_fill = Window.orderBy((F.col("cap") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    everything = Window.partitionBy()
    table = table.withColumn("total", F.sum("source_size").over(everything))
    table = table.withColumn("cap_before", F.coalesce(F.sum("cap").over(by_fill.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    table = table.withColumn("weight_left", F.sum("weight").over(by_fill.rowsBetween(0, Window.unboundedFollowing)))
    level = (F.col("total") - F.col("cap_before")) / F.col("weight_left")
    table = table.withColumn("level", level)
    # The first source in fill order that is not above its cap fixes the level for itself and all after it.
    table = table.withColumn("final", F.min(F.when(F.col("level") * F.col("weight") <= F.col("cap"), F.struct(F.col("cap") / F.col("weight"), F.col("level")))).over(everything)["level"])
    target = F.least(F.col("cap").cast("double"), F.col("weight") * F.coalesce(F.col("final"), F.col("level")))
    return table.select("source", "source_size", target.alias("target"))


def mix(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, max_epochs: int = MAX_EPOCHS, slices: int = SLICES, keep: tuple[str, ...] = ()) -> DataFrame:
    """Rows doc_id, size, source_size, target, taken (words taken, repeats counted) and the columns named in keep.

    Every source is read floor(target) words long: whole epochs first, then documents in order of their random key, the
    last one cut. Null texts and texts without words have size 0 and nothing is taken of them; a null source is a source
    of its own, the last; a row without an id has the key of its text, so such rows spread over the slices; repeated rows
    count each; an empty table gives none.
    """
    key = F.md5(F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("null/"), F.md5(F.coalesce(F.col("text").cast("string"), F.lit(""))))))
    width = len(f"{slices - 1:x}")
    rows = docs.select(
        "doc_id", "source", *[F.col(c).alias(f"keep_{c}") for c in keep],
        F.when(F.col("text").isNull(), 0).otherwise(F.regexp_count("text", F.lit(WORD))).cast("long").alias("size"), key.alias("key"),
    ).withColumns({"slice": F.substring("key", 1, width), "named": F.coalesce("source", F.lit("")), "unnamed": F.col("source").isNull()})
    if not keep:  # no texts to carry: words are counted once, for both passes
        rows = materialize(rows)
    parts = rows.groupBy("source", "named", "unnamed", "slice").agg(F.sum("size").alias("slice_size"))
    in_order = Window.partitionBy("named", "unnamed").orderBy("slice")
    parts = parts.withColumn("slice_start", F.sum("slice_size").over(in_order) - F.col("slice_size"))
    sizes = parts.groupBy("source").agg(F.sum("slice_size").alias("source_size"))
    plan = target_table(sizes, weights, max_epochs).select(F.coalesce("source", F.lit("")).alias("named"), F.col("source").isNull().alias("unnamed"), "source_size", "target")
    parts = parts.drop("source").join(plan, ["named", "unnamed"]).select("named", "unnamed", "slice", "slice_start", "source_size", "target")
    rows = rows.join(parts, ["named", "unnamed", "slice"])
    inside = Window.partitionBy("named", "unnamed", "slice").orderBy("key", F.col("doc_id").asc_nulls_last(), "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = rows.withColumn("before", F.col("slice_start") + F.sum("size").over(inside) - F.col("size"))
    budget = F.floor("target").cast("long")
    epochs = F.when(F.col("source_size") > 0, F.floor(budget / F.col("source_size"))).otherwise(0).cast("long")
    rest = budget - epochs * F.col("source_size")
    part = F.greatest(F.lit(0), F.least(rest - F.col("before"), F.col("size")))
    taken = epochs * F.col("size") + part
    return rows.select("doc_id", "source", "size", "source_size", "target", taken.cast("long").alias("taken"), epochs.alias("epochs"), part.cast("long").alias("cut"), *[F.col(f"keep_{c}").alias(c) for c in keep])


def mixed_corpus(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: each document's row as often as it is taken, the last time cut to the words that still fit.

    Columns beyond doc_id, text, source and n_chars may have any name.
    """

    def work(named: DataFrame) -> DataFrame:
        columns = named.columns
        rows = mix(named, keep=tuple(c for c in columns if c not in ("doc_id", "source")), **options)
        whole = rows.withColumn("copies", (F.col("epochs") + F.when((F.col("cut") > 0) & (F.col("cut") == F.col("size")), 1).otherwise(0)).cast("int"))
        whole = whole.where("copies > 0").withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies"))))
        cut = rows.where("cut > 0 and cut < size")
        pieces = cut.withColumn("text", F.expr(r"array_join(slice(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+', 0), 1, cast(cut as int)), ' ')"))
        out = whole.select(*columns).unionByName(pieces.select(*columns))
        if "n_chars" in columns:
            out = out.withColumn("n_chars", F.length("text").cast(named.schema["n_chars"].dataType))
        return out

    return guarded(docs, work)


ORACLE = r"""
with d as (select doc_id, source, md5(coalesce(cast(doc_id as varchar), 'null/' || md5(coalesce(text, '')))) as k,
        coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size from documents),
  s as (select source, sum(size)::bigint as source_size, [5, 2, 1][(row_number() over (order by source nulls last) - 1) % 3 + 1] as w from d group by source),
  f as (select *, source_size * 3 as cap, sum(source_size) over () as total,
        coalesce(sum(source_size * 3) over (order by (source_size * 3) / w, source nulls last rows between unbounded preceding and 1 preceding), 0) as before,
        sum(w) over (order by (source_size * 3) / w, source nulls last rows between current row and unbounded following) as wl from s),
  g as (select *, (total - before) / wl as lvl, cap / w as ratio from f),
  h as (select arg_min(lvl, ratio) as lvl from g where lvl * w <= cap),
  t as (select g.source, source_size, least(cap::double, w * h.lvl) as target from g cross join h),
  x as (select d.doc_id, d.size, t.source_size, t.target, floor(t.target)::bigint as b,
        (sum(d.size) over (partition by d.source order by d.k, d.doc_id nulls last, d.size rows unbounded preceding) - d.size)::bigint as before
        from d join t on d.source is not distinct from t.source)
select doc_id, size, source_size, target,
  ((case when source_size > 0 then b // source_size else 0 end) * size
   + greatest(0, least((case when source_size > 0 then b % source_size else 0 end) - before, size)))::bigint as taken from x
"""


def query(spark, sf_dir: str) -> DataFrame:
    return mix(spark.read.parquet(f"{sf_dir}/documents.parquet")).select("doc_id", "size", "source_size", "target", "taken")
