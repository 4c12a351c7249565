"""Relational operators that prepare inputs and targets and summarize results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kernelblocks.functions.kernels import dot_col
from kernelblocks.operators import prep
from kernelblocks.operators.prep import e
from kernelblocks.queries.registry import query
from kernelblocks.sources.tables import table


def r6(c, digits: int = 6):
    """Rounded, without a negative zero."""
    return F.round(c, digits) + F.lit(0.0)


@query("SELECT vec_id, label, len(embedding)::INT AS dims, round(embedding[1]::DOUBLE, 6) + 0.0 AS first_value FROM embeddings")
def scan_embeddings(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").select("vec_id", "label", F.size("embedding").alias("dims"), r6(e(0)).alias("first_value"))


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda v: v::DOUBLE * v::DOUBLE))), 6) AS norm FROM embeddings")
def vector_norms(spark: SparkSession, d: str) -> DataFrame:
    squares = F.aggregate("embedding", F.lit(0.0), lambda s, v: s + v.cast("double") * v.cast("double"))
    return table(spark, d, "embeddings").select("vec_id", F.round(F.sqrt(squares), 6).alias("norm"))


@query("SELECT a.vec_id, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) + 0.0 AS dot FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def dot_products(spark: SparkSession, d: str) -> DataFrame:
    v = table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("a"))
    after = v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("a").alias("b"))
    return v.join(after, "vec_id").select("vec_id", r6(dot_col(F.col("a"), F.col("b"))).alias("dot"))


_Z = "round((l.{0} - s.m_{0}) / s.s_{0}, 6) + 0.0 AS {0}_z"


@query(
    "WITH s AS (SELECT avg(l_quantity) AS m_l_quantity, stddev_pop(l_quantity) AS s_l_quantity, avg(l_discount) AS m_l_discount, stddev_pop(l_discount) AS s_l_discount FROM lineitem) "
    f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, {_Z.format('l_quantity')}, {_Z.format('l_discount')} FROM lineitem l CROSS JOIN s"
)
def standardize_lineitem(spark: SparkSession, d: str) -> DataFrame:
    z = prep.standardize(table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_discount"), ["l_quantity", "l_discount"])
    return z.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", r6("l_quantity_z").alias("l_quantity_z"), r6("l_discount_z").alias("l_discount_z"))


@query(
    "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 4) AS quantity FROM lineitem "
    "WHERE l_returnflag IN ('A', 'R') AND l_discount BETWEEN 0.02 AND 0.06 GROUP BY ALL"
)
def filter_reduced(spark: SparkSession, d: str) -> DataFrame:
    kept = table(spark, d, "lineitem").where(F.col("l_returnflag").isin("A", "R") & F.col("l_discount").between(0.02, 0.06))
    return kept.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 4).alias("quantity"))


@query("SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE (l_orderkey * 48271 + l_linenumber * 69621 + l_partkey * 31) % 2147483647 % 1000 < 100")
def hash_sample(spark: SparkSession, d: str) -> DataFrame:
    key = F.col("l_orderkey") * 48271 + F.col("l_linenumber") * 69621 + F.col("l_partkey") * 31
    return table(spark, d, "lineitem").where(F.pmod(key, F.lit(2147483647)) % 1000 < 100).select("l_orderkey", "l_linenumber", "l_partkey")


def _target(spark: SparkSession, d: str, value, name: str) -> DataFrame:
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", value.alias(name))


@query("SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) AS charge FROM lineitem")
def charge_target(spark: SparkSession, d: str) -> DataFrame:
    return _target(spark, d, F.round(prep.charge_col(), 6), "charge")


@query("SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(sin(l_quantity / 4) * cos(40.0::DOUBLE * l_discount), 6) + 0.0 AS ripple FROM lineitem")
def ripple_target(spark: SparkSession, d: str) -> DataFrame:
    return _target(spark, d, r6(prep.ripple_col()), "ripple")


@query("SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, CASE WHEN (l_quantity > 25) <> (l_discount > 0.05) THEN 1 ELSE -1 END AS checker FROM lineitem")
def checker_target(spark: SparkSession, d: str) -> DataFrame:
    return _target(spark, d, prep.checker_col(), "checker")


@query("SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, (5 * least(floor((l_quantity - 1) / 10), 4) + least(floor(round(l_discount * 100) / 2.2::DOUBLE), 4))::INT AS cell FROM lineitem")
def cells25_target(spark: SparkSession, d: str) -> DataFrame:
    return _target(spark, d, prep.cells_col(), "cell")


@query("SELECT vec_id, CASE WHEN embedding[1]::DOUBLE * embedding[2]::DOUBLE > 0 THEN 1 ELSE -1 END AS side FROM embeddings")
def xor01_target(spark: SparkSession, d: str) -> DataFrame:
    return prep.embedding_task(table(spark, d, "embeddings"), "xor01").select(F.col("row_id").alias("vec_id"), F.col("label").alias("side"))


@query(
    "WITH r AS (SELECT vec_id, embedding[1]::DOUBLE * embedding[1]::DOUBLE + embedding[2]::DOUBLE * embedding[2]::DOUBLE AS q FROM embeddings) "
    "SELECT vec_id, CASE WHEN q > (SELECT median(q) FROM r) THEN 1 ELSE -1 END AS side FROM r"
)
def shell01_target(spark: SparkSession, d: str) -> DataFrame:
    return prep.embedding_task(table(spark, d, "embeddings"), "shell01").select(F.col("row_id").alias("vec_id"), F.col("label").alias("side"))


@query("SELECT vec_id, (list_position(embedding[1:10], list_max(embedding[1:10])) - 1)::INT AS place FROM embeddings")
def argmax10_target(spark: SparkSession, d: str) -> DataFrame:
    return prep.embedding_task(table(spark, d, "embeddings"), "argmax10").select(F.col("row_id").alias("vec_id"), F.col("label").alias("place"))


@query("SELECT CASE WHEN label < 5 THEN 1 ELSE -1 END AS side, count(*) AS n, min(label) AS low, max(label) AS high FROM embeddings GROUP BY 1")
def binarize_split(spark: SparkSession, d: str) -> DataFrame:
    sides = prep.binarize(table(spark, d, "embeddings"), "label", 10)
    return sides.groupBy("side").agg(F.count("*").alias("n"), F.min("label").alias("low"), F.max("label").alias("high"))


@query(
    "SELECT n_name, p_brand, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(sum(p_retailprice), 2) AS price "
    "FROM lineitem JOIN part ON p_partkey = l_partkey JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey GROUP BY ALL"
)
def join_features(spark: SparkSession, d: str) -> DataFrame:
    li = table(spark, d, "lineitem").select("l_partkey", "l_suppkey", "l_extendedprice", "l_discount")
    part = table(spark, d, "part").select("p_partkey", "p_brand", "p_retailprice")
    supp = table(spark, d, "supplier").select("s_suppkey", "s_nationkey")
    nation = table(spark, d, "nation").select("n_nationkey", "n_name")
    # nation has a fixed 25 rows; part and supplier grow with the data and are left to the optimizer
    joined = li.join(part, li.l_partkey == part.p_partkey).join(supp, li.l_suppkey == supp.s_suppkey).join(F.broadcast(nation), supp.s_nationkey == nation.n_nationkey)
    revenue = F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount")))
    return joined.groupBy("n_name", "p_brand").agg(F.count("*").alias("n"), F.round(revenue, 2).alias("revenue"), F.round(F.sum("p_retailprice"), 2).alias("price"))


@query("SELECT doc_id, lang, quality, toxic FROM documents JOIN labels USING (doc_id)")
def labels_join(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").select("doc_id", "lang").join(table(spark, d, "labels"), "doc_id").select("doc_id", "lang", "quality", "toxic")


@query("SELECT doc_id, source FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def labelled_semi(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").select("doc_id", "source").join(table(spark, d, "labels"), "doc_id", "left_semi")


@query("SELECT doc_id, source FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def unlabelled_anti(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").select("doc_id", "source").join(table(spark, d, "labels"), "doc_id", "left_anti")


def _labelled(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").select("doc_id", "lang", "n_chars").join(table(spark, d, "labels"), "doc_id")


@query("SELECT lang, quality, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents JOIN labels USING (doc_id) GROUP BY ROLLUP (lang, quality)")
def label_rollup(spark: SparkSession, d: str) -> DataFrame:
    return _labelled(spark, d).rollup("lang", "quality").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("SELECT lang, quality, toxic, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY CUBE (lang, quality, toxic)")
def label_cube(spark: SparkSession, d: str) -> DataFrame:
    return _labelled(spark, d).cube("lang", "quality", "toxic").agg(F.count("*").alias("n"))


@query("SELECT label, count(*) AS n, count(DISTINCT embedding) AS n_distinct FROM embeddings GROUP BY label")
def class_counts(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").groupBy("label").agg(F.count("*").alias("n"), F.count_distinct("embedding").alias("n_distinct"))


@query()
def class_counts_approx(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_orderkey", 0.02).alias("orders"))


@query(
    "WITH c AS (SELECT label, k, avg(embedding[k]::DOUBLE) AS v FROM embeddings, range(1, 65) t(k) GROUP BY label, k) SELECT label, (k - 1)::INT AS dim, round(v, 6) + 0.0 AS mean FROM c"
)
def class_centroids(spark: SparkSession, d: str) -> DataFrame:
    cells = table(spark, d, "embeddings").select("label", F.posexplode("embedding").alias("dim", "v"))
    return cells.groupBy("label", "dim").agg(r6(F.avg(F.col("v").cast("double"))).alias("mean"))


@query(
    "WITH c AS (SELECT label, k, avg(embedding[k]::DOUBLE) AS v FROM embeddings, range(1, 65) t(k) GROUP BY label, k), "
    "g AS (SELECT vec_id, e.label, c.label AS guess, round(sum((embedding[k]::DOUBLE - v) ** 2), 9) AS dist FROM embeddings e JOIN c ON true GROUP BY ALL), "
    "p AS (SELECT vec_id, label, arg_min(guess, (dist, guess)) AS guess FROM g GROUP BY vec_id, label) "
    "SELECT count(*) AS n, sum((label = guess)::INT)::BIGINT AS hits, round(avg((label = guess)::INT), 6) AS accuracy FROM p"
)
def accuracy_nearest_centroid(spark: SparkSession, d: str) -> DataFrame:
    v = table(spark, d, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("dim", "v")).withColumn("v", F.col("v").cast("double"))
    # ten classes of 64 numbers: the centroids have a fixed size
    c = v.groupBy("label", "dim").agg(F.avg("v").alias("m")).withColumnRenamed("label", "guess")
    dist = v.join(F.broadcast(c), "dim").groupBy("vec_id", "label", "guess").agg(F.round(F.sum((F.col("v") - F.col("m")) ** 2), 9).alias("dist"))
    best = dist.groupBy("vec_id", "label").agg(F.min_by("guess", F.struct("dist", "guess")).alias("guess"))
    hit = (F.col("label") == F.col("guess")).cast("int")
    return best.agg(F.count("*").alias("n"), F.sum(hit).alias("hits"), F.round(F.avg(hit), 6).alias("accuracy"))


@query(
    "WITH p AS (SELECT label, CASE WHEN embedding[1] > 0 THEN 'up' ELSE 'down' END AS pred FROM embeddings) "
    "SELECT label, count(*) FILTER (pred = 'down') AS down, count(*) FILTER (pred = 'up') AS up FROM p GROUP BY label"
)
def confusion_pivot(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.measures import confusion

    scored = table(spark, d, "embeddings").select("label", F.when(e(0) > 0, "up").otherwise("down").alias("pred"))
    return confusion(scored, ["down", "up"])


@query(
    "WITH p AS (SELECT label, vec_id, (embedding[1] > 0)::INT AS hit FROM embeddings) "
    "SELECT label, vec_id, round(avg(hit) OVER w, 6) AS running, max(hit) OVER w AS best FROM p WINDOW w AS (PARTITION BY label ORDER BY vec_id ROWS UNBOUNDED PRECEDING)"
)
def window_running_accuracy(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("label").orderBy("vec_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    p = table(spark, d, "embeddings").select("label", "vec_id", (e(0) > 0).cast("int").alias("hit"))
    return p.select("label", "vec_id", F.round(F.avg("hit").over(w), 6).alias("running"), F.max("hit").over(w).alias("best"))


@query(
    "SELECT label, vec_id, CASE WHEN row_number() OVER (PARTITION BY label ORDER BY vec_id) % 5 = 0 THEN 'test' ELSE 'train' END AS part, ntile(4) OVER (PARTITION BY label ORDER BY vec_id)::INT AS fold FROM embeddings"
)
def stratified_split(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("label").orderBy("vec_id")
    part = F.when(F.row_number().over(w) % 5 == 0, "test").otherwise("train")
    return table(spark, d, "embeddings").select("label", "vec_id", part.alias("part"), F.ntile(4).over(w).alias("fold"))


@query(
    "WITH t AS (SELECT vec_id FROM embeddings WHERE vec_id % 5 = 0), r AS (SELECT vec_id FROM embeddings WHERE vec_id % 5 <> 0) "
    "SELECT 'both' AS part, count(*) AS n FROM (SELECT * FROM t INTERSECT SELECT * FROM r) UNION ALL "
    "SELECT 'either', count(*) FROM (SELECT * FROM t UNION SELECT * FROM r) UNION ALL "
    "SELECT 'rest', count(*) FROM (SELECT vec_id FROM embeddings EXCEPT SELECT * FROM t)"
)
def split_setops(spark: SparkSession, d: str) -> DataFrame:
    v = table(spark, d, "embeddings").select("vec_id")
    t, r = v.where("vec_id % 5 = 0"), v.where("vec_id % 5 <> 0")

    def count(df: DataFrame, name: str) -> DataFrame:
        return df.agg(F.count("*").alias("n")).select(F.lit(name).alias("part"), "n")

    return count(t.intersect(r), "both").union(count(t.union(r).distinct(), "either")).union(count(v.exceptAll(t), "rest"))


@query(
    "WITH g AS (SELECT lang, unnest([substr(lower(text), i, 3) FOR i IN range(1, length(text) - 1)]) AS gram FROM documents WHERE length(text) >= 3) "
    "SELECT lang, gram, count(*) AS n FROM g GROUP BY ALL"
)
def trigram_counts(spark: SparkSession, d: str) -> DataFrame:
    return prep.trigram_totals(table(spark, d, "documents"), "lang", "text")


@query("SELECT page_id, length(html)::INT AS n_html, length(trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ \\t\\n\\r]+', ' ', 'g')))::INT AS n_text FROM pages")
def page_text_length(spark: SparkSession, d: str) -> DataFrame:
    bare = F.trim(F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), "[ \\t\\n\\r]+", " "))
    return table(spark, d, "pages").select("page_id", F.length("html").alias("n_html"), F.length(bare).alias("n_text"))


@query("SELECT event_type, (props->>'k')::INT AS k, count(*) AS n FROM events GROUP BY ALL")
def json_props(spark: SparkSession, d: str) -> DataFrame:
    k = F.from_json("props", "k int").getField("k")
    return table(spark, d, "events").groupBy("event_type", k.alias("k")).agg(F.count("*").alias("n"))


@query(
    "SELECT event_id, hour(ts)::INT AS hour, round(sin(2 * pi() * hour(ts) / 24), 6) + 0.0 AS hour_sin, round(cos(2 * pi() * hour(ts) / 24), 6) + 0.0 AS hour_cos, round(ln(1 + value), 6) AS log_value FROM events"
)
def event_time_features(spark: SparkSession, d: str) -> DataFrame:
    h = F.hour("ts")
    turn = F.lit(2 * 3.141592653589793) * h / 24
    return table(spark, d, "events").select("event_id", h.alias("hour"), r6(F.sin(turn)).alias("hour_sin"), r6(F.cos(turn)).alias("hour_cos"), F.round(F.log1p("value"), 6).alias("log_value"))


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def events_tumbling(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.streaming.windows import tumbling

    return tumbling(table(spark, d, "events"))


@query(
    "WITH w AS (SELECT unnest([time_bucket(INTERVAL 30 MINUTE, ts), time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE]) AS start, value FROM events) "
    "SELECT start, count(*) AS n, round(avg(value), 6) AS mean FROM w GROUP BY start"
)
def events_sliding(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.streaming.windows import sliding

    return sliding(table(spark, d, "events"))


@query(
    "WITH g AS (SELECT user_id, ts, value, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events), "
    "s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM g) "
    "SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 6 HOUR AS stop, count(*) AS n FROM s GROUP BY user_id, no"
)
def events_session(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.streaming.windows import sessions

    return sessions(table(spark, d, "events"))


@query(
    "WITH p AS (SELECT user_id, ts, value FROM events WHERE event_type = 'purchase'), o AS (SELECT event_id, user_id, ts FROM events WHERE event_type <> 'purchase') "
    "SELECT o.event_id, o.user_id, max_by(p.value, (p.ts, p.value)) AS last_value FROM o LEFT JOIN p ON p.user_id = o.user_id AND p.ts <= o.ts GROUP BY ALL"
)
def asof_last_event(spark: SparkSession, d: str) -> DataFrame:
    from kernelblocks.operators.asof import last_before

    ev = table(spark, d, "events")
    left = ev.where("event_type <> 'purchase'").select("event_id", "user_id", "ts")
    right = ev.where("event_type = 'purchase'").select("user_id", "ts", F.col("value").alias("last_value"))
    return last_before(left, right, "user_id", "ts", "last_value").select("event_id", "user_id", "last_value")


@query(
    "WITH n AS (SELECT count(*) AS n FROM embeddings), b AS (SELECT i, n // 7 + (i < n % 7)::INT AS size FROM range(7) t(i), n) "
    "SELECT i::INT AS block, (sum(size) OVER (ORDER BY i) - size)::BIGINT AS low, size::BIGINT AS size FROM b"
)
def block_bounds(spark: SparkSession, d: str) -> DataFrame:
    """Bounds of seven even blocks, and the rows that the dealing puts in each."""
    from kernelblocks.functions.sqlfunctions import register
    from kernelblocks.plans.blocks import even_blocks

    register(spark)
    rows = table(spark, d, "embeddings").select(F.col("vec_id").alias("row_id"), F.col("embedding").alias("x"), F.col("label").alias("y"))
    even_blocks(rows, 7).groupBy("row_block").agg(F.count("*").alias("dealt")).createOrReplaceTempView("kb_dealt")
    return spark.sql(
        "SELECT block, low, coalesce(dealt, 0) AS size FROM (SELECT coalesce(sum(dealt), 0) AS n FROM kb_dealt) t, LATERAL kb_block_bounds(t.n, 7) LEFT JOIN kb_dealt ON row_block = block"
    )
