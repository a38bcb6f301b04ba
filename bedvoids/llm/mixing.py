"""Mixing sources to target weights by systematic sampling.

Targets are words. A source's target is its share by weight of the whole mix, but never more than `most`
times its own size; what it can't take is shared again by weight among the others. Within a source every
document is expected target / size times. These expectations are summed up along the source, one random
offset is added, and a document is emitted once for every integer that its part of the sum crosses.
Documents stand in order of size, so neighbours stand for each other and the words taken stay within
about one document of the target.

Null texts have size 0 and take 0 words; documents without a source form the last source. Rows with the
same id are documents of their own; rows alike in every column stand for each other, so they are kept once and
emitted as often as all of them together. The random offset is a hash of the source and the seed: reruns agree.
Extra columns are ignored, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DataType, MapType, VariantType

from .store import global_rank, store

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (3, 1, 2)


def size_of(text: str) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def row_keys(df: DataFrame) -> list[Column]:
    """Two hashes, a and b, of all columns of a row; rows alike in every column agree in them."""

    def plain(name: str, kind: DataType) -> Column:
        c = df[f"`{name}`"]
        return F.to_json(F.struct(c)) if isinstance(kind, VariantType | MapType) or "map<" in kind.simpleString() or "variant" in kind.simpleString() else c

    # nulls leave a hash as it was, so which columns are null is hashed too
    cols = [plain(f.name, f.dataType) for f in df.schema] + [df[f"`{f.name}`"].isNull() for f in df.schema]
    return [F.xxhash64(*cols).alias("a"), F.xxhash64(F.lit(9), *cols).alias("b")]


def offset(seed: int) -> Column:
    """A number in [0, 1) from source and seed, the same in every engine that has md5."""
    name = F.concat(F.lit(f"{seed}:"), F.coalesce(F.concat(F.lit("="), "source"), F.lit("-")))
    return F.conv(F.substring(F.md5(name), 1, 13), 16, 10).cast("double") / float(1 << 52)


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: tuple[int, int] = (3, 2), most: int = 2) -> DataFrame:
    """source, source_size -> the same with target. `share`: words of the mix as a fraction of all words."""
    ranked = global_rank(sizes, [F.col("source").asc_nulls_last()], name="at")
    pattern = F.array(*[F.lit(int(w)) for w in weights])
    ranked = store(ranked.withColumn("weight", F.element_at(pattern, (F.pmod(F.col("at") - 1, F.lit(len(weights))) + 1).cast("int"))).drop("at"), "sources")
    up, down = share
    full = F.lit(False)
    held, free, last = 0, None, -1
    while True:  # each round fixes the sources that stand above their limit; only sums come to the driver
        row = ranked.agg(
            F.sum("source_size").alias("total"),
            F.coalesce(F.sum(F.when(full, F.col("source_size") * most)), F.lit(0)).alias("held"),
            F.coalesce(F.sum(F.when(~full, F.col("weight"))), F.lit(0)).alias("free"),
            F.count_if(full).alias("n"),
        ).first()
        total, held, free = int(row["total"] or 0), int(row["held"]), int(row["free"])
        level = F.lit(float(total * up - held * down)) / F.lit(float(max(free, 1) * down)) * F.col("weight")
        if row["n"] == last or not free:
            break
        last = row["n"]
        full = full | (level > F.col("source_size") * F.lit(float(most)))
    return ranked.select("source", "source_size", F.when(full, F.col("source_size") * F.lit(float(most))).otherwise(level).alias("target"))


def _planned(docs: DataFrame, weights: tuple[int, ...], share: tuple[int, int], most: int, seed: int, keys: list[Column]) -> DataFrame:
    names = [f"key_{k}" for k in range(len(keys))]
    sized = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), size_of("text").alias("size"), *[k.alias(n) for k, n in zip(keys, names, strict=True)])
    sized = store(sized, "sizes")
    ranked = global_rank(sized, [F.col("source").asc_nulls_last(), F.col("size"), F.col("doc_id"), *map(F.col, names)], within="source", name="at")
    goals = targets(sized.groupBy("source").agg(F.sum("size").alias("source_size")), weights, share, most).withColumn("u", offset(seed)).withColumnRenamed("source", "_s")
    both = ranked.join(goals, F.col("source").eqNullSafe(F.col("_s")))
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    crossed = F.floor(F.col("u") + rate * F.col("at")) - F.floor(F.col("u") + rate * (F.col("at") - 1))
    copies = F.least(crossed, F.lit(most)).cast("long")
    return both.withColumn("copies", copies).select("doc_id", "size", "source", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"), *names)


def mix(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: tuple[int, int] = (3, 2), most: int = 2, seed: int = 1) -> DataFrame:
    """doc_id, size, source, source_size, target, copies, taken for each row of `docs`."""
    return _planned(docs, weights, share, most, seed, [])


def mixed(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: tuple[int, int] = (3, 2), most: int = 2, seed: int = 1) -> DataFrame:
    """`docs` as the mix takes them: rows repeat as often as they are taken, with the number of the copy in mix_copy (mix_copy_ if that name is taken)."""
    taken = _planned(docs, weights, share, most, seed, row_keys(docs))
    plan = taken.groupBy("key_0", "key_1").agg(F.sum("copies").alias("copies"), F.count(F.lit(1)).alias("m")).where("copies > 0")
    rows = docs.select(*row_keys(docs), F.struct("*").alias("row"))
    there = rows.join(plan, (F.col("a") == F.col("key_0")) & (F.col("b") == F.col("key_1")))
    # rows alike in every column: one of them stands for all
    once = there.where("m > 1").groupBy("a", "b").agg(F.any_value("row").alias("row"), F.any_value("copies").alias("copies"))
    name = "mix_copy"
    while name in docs.columns:
        name += "_"
    copies = F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))).alias(name)
    return there.where("m = 1").select("row", "copies").unionByName(once.select("row", "copies")).select("row", copies).select("row.*", name)


SQL = r"""
WITH sized AS (
  SELECT CAST(doc_id AS BIGINT) AS doc_id, source,
         CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size
  FROM documents
), sources AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source
), weighed AS (
  SELECT *, [3, 1, 2][CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 AS INT) + 1] AS weight FROM sources
), steps AS (
  SELECT *,
    CAST(coalesce(sum(source_size) OVER before_, 0) AS BIGINT) AS held,
    CAST(sum(weight) OVER () - coalesce(sum(weight) OVER before_, 0) AS BIGINT) AS free,
    CAST(sum(source_size) OVER () AS BIGINT) AS total
  FROM weighed
  WINDOW before_ AS (ORDER BY CAST(source_size AS DOUBLE) / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)
), level AS (
  SELECT total * 3 - held * 4 AS rest, free FROM steps
  WHERE CAST(total * 3 - held * 4 AS DOUBLE) / CAST(free * 2 AS DOUBLE) * weight <= source_size * CAST(2 AS DOUBLE)
  ORDER BY free DESC LIMIT 1
), goals AS (
  SELECT w.source, w.source_size,
    CASE WHEN CAST(l.rest AS DOUBLE) / CAST(l.free * 2 AS DOUBLE) * w.weight > w.source_size * CAST(2 AS DOUBLE)
      THEN w.source_size * CAST(2 AS DOUBLE) ELSE CAST(l.rest AS DOUBLE) / CAST(l.free * 2 AS DOUBLE) * w.weight END AS target,
    CAST(CAST('0x' || substr(md5('1:' || coalesce('=' || w.source, '-')), 1, 13) AS BIGINT) AS DOUBLE) / CAST(4503599627370496 AS DOUBLE) AS u
  FROM weighed w CROSS JOIN level l
), ranked AS (
  SELECT s.*, g.source_size, g.target, g.u,
    CASE WHEN g.source_size > 0 THEN g.target / g.source_size ELSE 0 END AS rate,
    row_number() OVER (PARTITION BY s.source ORDER BY s.size, s.doc_id) AS place
  FROM sized s JOIN goals g ON s.source IS NOT DISTINCT FROM g.source
)
SELECT doc_id, size, source_size, target,
  CAST(least(floor(u + rate * place) - floor(u + rate * (place - 1)), 2) AS BIGINT) * size AS taken
FROM ranked
"""
