"""Edge lists: normal form, readers, writers, and the graphs built from the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def edges_from(df: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """Canonical simple undirected edges: src < dst, distinct, no loops, no nulls. One shuffle (distinct)."""
    a, b = F.col(src), F.col(dst)
    return df.where(a.isNotNull() & b.isNotNull() & (a != b)).select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst")).distinct()


def arcs(edges: DataFrame) -> DataFrame:
    """Both directions, by exploding each row once instead of reading the edges twice."""
    both = F.explode(F.array(F.struct(F.col("src").alias("src"), F.col("dst").alias("dst")), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst"))))
    return edges.select(both.alias("e")).select("e.src", "e.dst")


def degrees(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("degree"))


def read_edge_text(spark: SparkSession, path: str, sep: str = r"\s+", comment: str = "#") -> DataFrame:
    """Edge list in text, two ids a line, comment lines allowed."""
    lines = spark.read.text(path).where(~F.startswith(F.ltrim("value"), F.lit(comment)) & (F.length(F.trim("value")) > 0))
    parts = F.split(F.trim("value"), sep)
    return edges_from(lines.select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst")))


def read_edges(spark: SparkSession, path: str, kind: str = "parquet", src: str = "src", dst: str = "dst", **options) -> DataFrame:
    return edges_from(spark.read.format(kind).options(**options).load(path), src, dst)


def write_edges(edges: DataFrame, path: str, *partition_by: str, kind: str = "parquet") -> None:
    edges.write.format(kind).partitionBy(*partition_by).save(path)


def write_bucketed(edges: DataFrame, table: str, buckets: int, path: str) -> None:
    """Edges bucketed and sorted by src, for joins without a further shuffle."""
    edges.write.bucketBy(buckets, "src").sortBy("src").option("path", path).saveAsTable(table)


def dense_ids(vertices: DataFrame, key: str = "key") -> DataFrame:
    """(id, key): consecutive ids by hash partition offsets, without a global sort or a single task."""
    parts = vertices.select(key).distinct().repartition(key).select(key, F.spark_partition_id().alias("p"))
    from pyspark.sql import Window

    from ..runtime import written

    parts = written(parts.withColumn("k", F.row_number().over(Window.partitionBy("p").orderBy(key)) - 1), "ids")
    sizes, before = sorted((r.p, r["count"]) for r in parts.groupBy("p").count().collect()), {}  # one row per partition
    total = 0
    for p, n in sizes:
        before[p], total = total, total + n
    offset = F.create_map(*[F.lit(x) for kv in before.items() for x in kv]) if before else F.create_map().cast("map<int,int>")
    return parts.select((F.col("k") + F.element_at(offset, F.col("p"))).cast("long").alias("id"), F.col(key).alias("key"))


# ---------------------------------------------------------------- graphs of the given tables

_LETTERS = r"\p{L}+"


def _tokens(df: DataFrame) -> DataFrame:
    return df.withColumn("tokens", F.regexp_extract_all(F.lower("text"), F.lit(_LETTERS), F.lit(0)))


def _part_supp(spark, d):
    return load_table(spark, d, "lineitem").select((2 * F.col("l_partkey")).alias("src"), (2 * F.col("l_suppkey") + 1).alias("dst"))


def _order_lines(spark, d):
    o, li = load_table(spark, d, "orders").select("o_orderkey", "o_custkey"), load_table(spark, d, "lineitem").select("l_orderkey", "l_suppkey", "l_partkey")
    return o.join(li, o["o_orderkey"] == li["l_orderkey"])


def _cust_supp(spark, d):
    return _order_lines(spark, d).select((2 * F.col("o_custkey")).alias("src"), (2 * F.col("l_suppkey") + 1).alias("dst"))


def _cust_part(spark, d):
    return _order_lines(spark, d).select((2 * F.col("o_custkey")).alias("src"), (2 * F.col("l_partkey") + 1).alias("dst"))


def _pairs_within(df: DataFrame, group: list[str], member: str) -> DataFrame:
    """Pairs of distinct members of a group; groups of the given tables are bounded by an order's lines or a bucket."""
    one = df.select(*group, member).distinct()
    return one.withColumnRenamed(member, "src").join(one.withColumnRenamed(member, "dst"), group).where("src < dst").select("src", "dst")


def _copart(spark, d):
    return _pairs_within(load_table(spark, d, "lineitem").select("l_orderkey", "l_partkey"), ["l_orderkey"], "l_partkey")


def _cosupp(spark, d):
    return _pairs_within(load_table(spark, d, "lineitem").select("l_orderkey", "l_suppkey"), ["l_orderkey"], "l_suppkey")


def _part_day(spark, d):
    day = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1970-01-01").cast("date")).cast("long")
    return load_table(spark, d, "lineitem").select((2 * F.col("l_partkey")).alias("src"), (2 * day + 1).alias("dst"))


def _word_adjacency(spark, d):
    t = _tokens(load_table(spark, d, "documents").select("text"))
    pairs = F.explode(F.arrays_zip(F.expr("slice(tokens, 1, greatest(size(tokens) - 1, 0))").alias("a"), F.expr("slice(tokens, 2, greatest(size(tokens) - 1, 0))").alias("b")))
    return t.select(pairs.alias("p")).select(F.col("p.a").alias("src"), F.col("p.b").alias("dst"))


def _doc_word(spark, d):
    t = _tokens(load_table(spark, d, "documents").select("doc_id", "text"))
    return t.select(F.concat(F.lit("d"), F.col("doc_id").cast("string")).alias("src"), F.explode(F.transform(F.array_distinct("tokens"), lambda x: F.concat(F.lit("w"), x))).alias("dst"))


def _conv_word(spark, d):
    t = _tokens(load_table(spark, d, "conversations").select("conv_id", "text"))
    return t.select(F.concat(F.lit("c"), F.col("conv_id").cast("string")).alias("src"), F.explode(F.transform(F.array_distinct("tokens"), lambda x: F.concat(F.lit("w"), x))).alias("dst"))


def _page_link(spark, d):
    t = load_table(spark, d, "pages").select("page_id", "html")
    return t.select(F.concat(F.lit("p"), F.col("page_id").cast("string")).alias("src"), F.explode(F.transform(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1)), lambda x: F.concat(F.lit("h"), x))).alias("dst"))


def _user_bucket(unit: str, *more: str):
    def build(spark, d):
        from ..operators import pairs

        one = user_slots(spark, d, unit, *more)
        if pairs.pair_count(one, ["slot", *more]) > pairs.PAIR_ROWS:
            return pairs.sharing_pairs(pairs.member_sets(one, ["slot", *more], "user_id"))
        return _pairs_within(one, ["slot", *more], "user_id").distinct()

    return build


def user_slots(spark, d, unit: str, *more: str) -> DataFrame:
    """(slot, *more, user_id), distinct: the users of each bucket, written."""
    from ..runtime import written

    ev = load_table(spark, d, "events").select(F.date_trunc(unit, "ts").alias("slot"), "user_id", *more).dropna()
    return written(ev.distinct(), "user-slots")


def _vec_near(spark, d, threshold: float = 0.3):
    e = load_table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))
    e = e.select("vec_id", F.transform("v", lambda x: x / norm).alias("v"))
    return near_pairs(e, threshold)


#: Vectors of a block: two blocks and a strip of their products are a few MB in a task.
VECTOR_BLOCK = 4096


def near_pairs(unit: DataFrame, threshold: float) -> DataFrame:
    """(src, dst): ids of unit vectors (vec_id, v array<double>) whose product is at least the threshold, every pair by
    one matrix product of two blocks. Products within rounding of the threshold are summed again element by element."""
    import numpy as np
    import pyarrow as pa

    whole = unit.where("vec_id is not null and v is not null and not exists(v, x -> x is null)")
    blocks = max(1, -(-whole.count() // VECTOR_BLOCK))
    own = whole.select("vec_id", "v", F.size("v").alias("size"), F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).alias("b"))
    sent = own.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select("vec_id", "v", "size", "b", F.least("b", "k").alias("lo"), F.greatest("b", "k").alias("hi"))

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        size, lo, hi = (x.as_py() for x in key)
        ids, block = table["vec_id"].to_numpy(), table["b"].to_numpy()
        v = np.concatenate([c.flatten().to_numpy() for c in table["v"].chunks]).reshape(len(ids), size)
        a, b = np.flatnonzero(block == lo), np.flatnonzero(block == hi)
        found = [np.zeros((2, 0), np.int64)]
        for at in range(0, len(a), 512):
            left = a[at : at + 512]
            dot = v[left] @ v[b].T
            x, y = np.nonzero(dot >= threshold - 1e-9)
            x, y, value = left[x], b[y], dot[x, y]
            close = np.flatnonzero(np.abs(value - threshold) <= 1e-9)
            again = np.zeros(len(close))
            for k in range(size):
                again += v[x[close], k] * v[y[close], k]
            value[close] = again
            first, second = ids[x], ids[y]
            keep = (value >= threshold) & ((first < second) if lo == hi else (first != second))
            found.append(np.stack([np.minimum(first, second)[keep], np.maximum(first, second)[keep]]))
        src, dst = np.concatenate(found, 1)
        return pa.table({"src": src, "dst": dst})

    return sent.groupBy("size", "lo", "hi").applyInArrow(run, "src long, dst long")


BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "part_supp": _part_supp,
    "cust_supp": _cust_supp,
    "cust_part": _cust_part,
    "copart": _copart,
    "cosupp": _cosupp,
    "part_day": _part_day,
    "word_adjacency": _word_adjacency,
    "doc_word": _doc_word,
    "conv_word": _conv_word,
    "page_link": _page_link,
    "user_hour": _user_bucket("hour"),
    "user_hour_type": _user_bucket("hour", "event_type"),
    "user_minute": _user_bucket("minute"),
    "vec_near": _vec_near,
}


#: Graphs whose builders give canonical edges already.
CANONICAL = ("user_hour", "user_hour_type", "user_minute")


def graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Canonical edges of a named graph."""
    rows = BUILDERS[name](spark, sf_dir)
    if name == "doc_word" and has_unique(load_table(spark, sf_dir, "documents"), "doc_id"):
        return rows.where("src is not null").select("src", "dst")  # a document's words are distinct, and no word is a document
    return rows if name in CANONICAL else edges_from(rows)


def has_unique(df: DataFrame, key: str) -> bool:
    """Whether no value of the key but null is there twice."""
    return df.where(F.col(key).isNotNull()).groupBy(key).count().where("count > 1").isEmpty()


# ---------------------------------------------------------------- synthetic graphs


def clique_ladder(spark: SparkSession, most: int, least: int = 2) -> DataFrame:
    """Disjoint cliques of every size; a vertex of the clique of size k has coreness k - 1. Ids: 1000 k + i."""
    k = spark.range(least, most + 1).select(F.col("id").alias("k"))
    one = k.select("k", F.explode(F.sequence(F.lit(0), (F.col("k") - 1).cast("int"))).alias("i"))
    pair = one.select("k", "i", F.explode(F.sequence(F.lit(0), (F.col("k") - 1).cast("int"))).alias("j")).where("i < j")
    return pair.select((1000 * F.col("k") + F.col("i")).alias("src"), (1000 * F.col("k") + F.col("j")).alias("dst"))


def random_graph(spark: SparkSession, n: int, m: int, seed: int = 0) -> DataFrame:
    """About m edges between n vertices, drawn by a hash of the row number (the same on every retry)."""
    end = lambda side: F.pmod(F.xxhash64(F.lit(seed), F.lit(side), "id"), F.lit(n)).alias(side)
    return edges_from(spark.range(m).select(end("src"), end("dst")))


def planted_core(spark: SparkSession, n: int, m: int, core: int, seed: int = 0) -> DataFrame:
    """A random graph with a clique planted on the first `core` vertices."""
    ids = spark.range(core).select(F.col("id").alias("src"))
    clique = ids.join(spark.range(core).select(F.col("id").alias("dst")), F.col("src") < F.col("dst"))
    return edges_from(random_graph(spark, n, m, seed).unionByName(clique))


def path_graph(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))


def star_graph(spark: SparkSession, leaves: int) -> DataFrame:
    return spark.range(1, leaves + 1).select(F.lit(0).cast("long").alias("src"), F.col("id").alias("dst"))


def cycle_graph(spark: SparkSession, n: int) -> DataFrame:
    """A cycle of n vertices: coreness 2 everywhere."""
    return edges_from(spark.range(n).select(F.col("id").alias("src"), ((F.col("id") + 1) % n).alias("dst")))


def grid_graph(spark: SparkSession, rows: int, columns: int) -> DataFrame:
    """A rectangular grid: coreness 2 everywhere (from 2 x 2 on)."""
    cell = spark.range(rows * columns).select("id", (F.col("id") % columns).alias("x"), F.floor(F.col("id") / columns).alias("y"))
    ends = F.array(F.when(F.col("x") < columns - 1, F.col("id") + 1), F.when(F.col("y") < rows - 1, F.col("id") + columns))
    return cell.select(F.col("id").alias("src"), F.explode(ends).alias("dst")).where("dst is not null")


def hub_groups(df: DataFrame, group: list[str], member: str, most: int) -> DataFrame:
    """Groups of more than `most` distinct members with the pairs that they would make: asked before a pairing, which
    drops none of them."""
    size = df.select(*group, member).distinct().groupBy(*group).agg(F.count(F.lit(1)).alias("members"))
    return size.where(F.col("members") > most).withColumn("pairs", (F.col("members") * (F.col("members") - 1) / 2).cast("long"))
