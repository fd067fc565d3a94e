"""Tables to transactions: (tid, items array<string>, label boolean) for ten encodings.

Items are `attribute=value` texts, sorted and distinct inside a transaction.  Nulls give no item.  Labels are never a function of the items.
`SQL` holds the same for DuckDB, with the items joined by commas.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import load


def items_of(*items: Column) -> Column:
    """The non-null items, sorted and distinct."""
    return F.sort_array(F.array_distinct(F.filter(F.array(*items), lambda x: x.isNotNull())))


def attr(name: str, value: Column | str) -> Column:
    """Null where the value is."""
    return F.concat(F.lit(f"{name}="), (F.col(value) if isinstance(value, str) else value).cast("string"))


def bins(name: str, value: Column, edges: list[float]) -> Column:
    """Number of edges strictly below the value."""
    return attr(name, sum(((value > e).cast("int") for e in edges), F.lit(0)))


def baskets(rows: DataFrame, key: str | list[str], item: Column) -> DataFrame:
    """One transaction for each key, of its distinct items."""
    keys = [key] if isinstance(key, str) else key
    return rows.select(*keys, item.alias("item")).where("item is not null").groupBy(*keys).agg(F.array_sort(F.collect_set("item")).alias("items"))


def order_attributes(spark: SparkSession, d: str) -> DataFrame:
    """o_orderkey, label, and the six attributes of an order as columns ending in the item or null; one scan of orders and two joins."""
    orders, customer, nation = load(spark, d, "orders"), load(spark, d, "customer"), load(spark, d, "nation")
    edges = orders.agg(F.percentile("o_totalprice", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75))).alias("edges"))
    who = customer.join(nation, customer.c_nationkey == nation.n_nationkey).select("c_custkey", "c_mktsegment", "n_regionkey", "c_acctbal")
    price = sum(((F.col("o_totalprice") > F.col("edges")[i]).cast("int") for i in range(3)), F.lit(0))
    return orders.join(who, orders.o_custkey == who.c_custkey).crossJoin(F.broadcast(edges)).select(
        "o_orderkey", (F.col("c_acctbal") >= 5000).alias("label"),
        attr("pri", "o_orderpriority").alias("pri"), attr("quart", price).alias("quart"), attr("region", "n_regionkey").alias("region"),
        attr("seg", "c_mktsegment").alias("seg"), attr("status", "o_orderstatus").alias("status"), attr("year", F.year("o_orderdate")).alias("year"),
    )


ORDER_ATTRIBUTES = ("pri", "quart", "region", "seg", "status", "year")


def order_dims(spark: SparkSession, d: str) -> DataFrame:
    return order_attributes(spark, d).select(F.col("o_orderkey").alias("tid"), items_of(*map(F.col, ORDER_ATTRIBUTES)).alias("items"), "label")


def customer_brands(spark: SparkSession, d: str) -> DataFrame:
    line, orders, part, customer = (load(spark, d, t) for t in ("lineitem", "orders", "part", "customer"))
    bought = line.join(orders, line.l_orderkey == orders.o_orderkey).join(part, line.l_partkey == part.p_partkey)
    return baskets(bought, "o_custkey", attr("brand", "p_brand")).join(customer, F.col("o_custkey") == F.col("c_custkey")).select(F.col("c_custkey").alias("tid"), "items", (F.col("c_acctbal") >= 5000).alias("label"))


def embed_signs(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "embeddings")
    on = F.filter(F.transform("embedding", lambda x, i: F.when(x > 0, F.concat(F.lit("d"), F.lpad(i.cast("string"), 2, "0")))), lambda x: x.isNotNull())
    return e.select(F.col("vec_id").alias("tid"), F.array_sort(on).alias("items"), (F.col("label") < 5).alias("label"))


def order_profile(spark: SparkSession, d: str) -> DataFrame:
    line, part = load(spark, d, "lineitem"), load(spark, d, "part")
    lines = line.join(part, line.l_partkey == part.p_partkey)
    each = lines.select("l_orderkey", F.explode(F.array(attr("brand", "p_brand"), attr("flag", "l_returnflag"), attr("line", "l_linestatus"), attr("type", "p_type"))).alias("item"))
    return baskets(each, "l_orderkey", F.col("item")).withColumnRenamed("items", "own").join(order_attributes(spark, d), F.col("l_orderkey") == F.col("o_orderkey")).select(
        F.col("o_orderkey").alias("tid"), F.array_sort(F.array_union("own", items_of(*map(F.col, ORDER_ATTRIBUTES)))).alias("items"), "label"
    )


def userday_events(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "events").withColumn("day", F.to_date("ts"))
    k = F.get_json_object("props", "$.k").cast("int")
    each = e.select("user_id", "day", "value", F.explode(F.array(attr("type", "event_type"), attr("slot", F.floor(F.hour("ts") / 4)), attr("k", F.floor(k / 10)), attr("wday", F.dayofweek("ts")))).alias("item"))
    rows = baskets(each, ["user_id", "day"], F.col("item"))
    sums = e.groupBy("user_id", "day").agg(F.round(F.sum("value"), 6).alias("v"))
    middle = sums.agg(F.median("v").alias("m"))
    return rows.join(sums, ["user_id", "day"]).crossJoin(F.broadcast(middle)).select(F.concat_ws(":", F.col("user_id").cast("string"), F.col("day").cast("string")).alias("tid"), "items", (F.col("v") > F.col("m")).alias("label"))


def doc_words(spark: SparkSession, d: str) -> DataFrame:
    docs, labels = load(spark, d, "documents"), load(spark, d, "labels")
    words = F.filter(F.split(F.lower("text"), r"[^\p{L}\p{N}_]+"), lambda w: w != "")
    return docs.join(labels, "doc_id").select(F.col("doc_id").alias("tid"), F.array_sort(F.array_distinct(words)).alias("items"), (F.col("quality") == 1).alias("label"))


def order_parts(spark: SparkSession, d: str) -> DataFrame:
    return baskets(load(spark, d, "lineitem"), "l_orderkey", F.lpad(F.col("l_partkey").cast("string"), 9, "0")).select(F.col("l_orderkey").alias("tid"), "items", F.lit(None).cast("boolean").alias("label"))


def line_attrs(spark: SparkSession, d: str) -> DataFrame:
    """lineitem has no key: tid is the hash of the row's items, and equal rows repeat.  Orders meet their customers first, so that lines are shuffled twice only."""
    line, orders, part, customer, nation = (load(spark, d, t) for t in ("lineitem", "orders", "part", "customer", "nation"))
    of = orders.join(customer.join(nation, customer.c_nationkey == nation.n_nationkey), orders.o_custkey == customer.c_custkey)
    j = line.join(part, line.l_partkey == part.p_partkey).join(of, line.l_orderkey == of.o_orderkey)
    items = items_of(
        attr("brand", "p_brand"), attr("disc", F.round(F.col("l_discount") * 100).cast("int")), attr("flag", "l_returnflag"), attr("pri", "o_orderpriority"), attr("qty", F.floor((F.col("l_quantity") - 1) / 10)),
        attr("region", "n_regionkey"), attr("seg", "c_mktsegment"), attr("stat", "l_linestatus"), attr("tax", F.round(F.col("l_tax") * 100).cast("int")), attr("type", "p_type"),
    )
    rows = j.select(items.alias("items"), (F.col("l_shipdate") >= F.lit("1998-06-01").cast("timestamp_ntz")).alias("label"))
    return rows.select(F.md5(F.array_join("items", ",")).alias("tid"), "items", "label")


def page_tags(spark: SparkSession, d: str) -> DataFrame:
    tags = F.regexp_extract_all("html", F.lit(r"<([a-z][a-z0-9]*)"), 1)
    return load(spark, d, "pages").select(F.col("page_id").alias("tid"), F.array_sort(F.array_distinct(tags)).alias("items"), F.lit(None).cast("boolean").alias("label"))


def conv_words(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "conversations")
    words = F.filter(F.split(F.lower("text"), r"[^\p{L}\p{N}_]+"), lambda w: w != "")
    each = c.select("conv_id", "role", F.explode(words).alias("w"))
    label = c.groupBy("conv_id").agg((F.max((F.col("role") == "system").cast("int")) == 1).alias("label"))
    return baskets(each, "conv_id", F.concat_ws("=", "role", "w")).join(label, "conv_id").select(F.col("conv_id").alias("tid"), "items", "label")


ENCODINGS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "order_dims": order_dims, "customer_brands": customer_brands, "embed_signs": embed_signs, "order_profile": order_profile, "userday_events": userday_events,
    "doc_words": doc_words, "order_parts": order_parts, "line_attrs": line_attrs, "page_tags": page_tags, "conv_words": conv_words,
}

ORDER_SQL = """SELECT o_orderkey, c_acctbal >= 5000 AS label, 'pri=' || o_orderpriority AS pri,
 'quart=' || (CAST(o_totalprice > e[1] AS INT) + CAST(o_totalprice > e[2] AS INT) + CAST(o_totalprice > e[3] AS INT)) AS quart, 'region=' || n_regionkey AS region,
 'seg=' || c_mktsegment AS seg, 'status=' || o_orderstatus AS status, 'year=' || year(o_orderdate) AS year
 FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey, (SELECT quantile_cont(o_totalprice, [0.25, 0.5, 0.75]) AS e FROM orders)"""
_JOIN = "array_to_string(list_sort(list_distinct({})), ',')"
_WORDS = r"list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}_]+'), lambda w: w <> '')"
SQL = {
    "order_dims": f"SELECT o_orderkey AS tid, concat_ws(',', pri, quart, region, seg, status, year) AS items, label FROM ({ORDER_SQL})",
    "customer_brands": f"SELECT c_custkey AS tid, {_JOIN.format('list(' + chr(39) + 'brand=' + chr(39) + ' || p_brand)')} AS items, any_value(c_acctbal) >= 5000 AS label FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN customer ON o_custkey = c_custkey GROUP BY c_custkey",
    "embed_signs": "SELECT vec_id AS tid, coalesce((SELECT string_agg('d' || lpad(CAST(i - 1 AS VARCHAR), 2, '0'), ',' ORDER BY i) FROM (SELECT unnest(embedding) AS x, generate_subscripts(embedding, 1) AS i) WHERE x > 0), '') AS items, label < 5 AS label FROM embeddings",
    "order_profile": f"""WITH own AS (SELECT l_orderkey, list('brand=' || p_brand) || list('flag=' || l_returnflag) || list('line=' || l_linestatus) || list('type=' || p_type) AS i FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1)
SELECT o_orderkey AS tid, {_JOIN.format('i || [pri, quart, region, seg, status, year]')} AS items, label FROM own JOIN ({ORDER_SQL}) ON l_orderkey = o_orderkey""",
    "userday_events": f"""WITH e AS (SELECT *, CAST(ts AS DATE) AS day FROM events), t AS (SELECT user_id, day, round(sum(value), 6) AS v,
 {_JOIN.format("list('type=' || event_type) || list('slot=' || (hour(ts) // 4)) || list('k=' || (CAST(json_extract_string(props, '$.k') AS INT) // 10)) || list('wday=' || (dayofweek(ts) + 1))")} AS items FROM e GROUP BY 1, 2)
SELECT user_id || ':' || day AS tid, items, v > (SELECT median(v) FROM t) AS label FROM t""",
    "doc_words": f"SELECT doc_id AS tid, {_JOIN.format(_WORDS)} AS items, quality = 1 AS label FROM documents JOIN labels USING (doc_id)",
    "order_parts": f"SELECT l_orderkey AS tid, {_JOIN.format('list(lpad(CAST(l_partkey AS VARCHAR), 9, ' + chr(39) + '0' + chr(39) + '))')} AS items, CAST(NULL AS BOOLEAN) AS label FROM lineitem GROUP BY 1",
    "line_attrs": """SELECT md5(items) AS tid, items, label FROM (SELECT concat_ws(',', 'brand=' || p_brand, 'disc=' || CAST(round(l_discount * 100) AS INT), 'flag=' || l_returnflag, 'pri=' || o_orderpriority, 'qty=' || CAST(floor((l_quantity - 1) / 10) AS INT),
 'region=' || n_regionkey, 'seg=' || c_mktsegment, 'stat=' || l_linestatus, 'tax=' || CAST(round(l_tax * 100) AS INT), 'type=' || p_type) AS items, l_shipdate >= TIMESTAMP '1998-06-01' AS label
 FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey)""",
    "page_tags": f"SELECT page_id AS tid, {_JOIN.format('regexp_extract_all(html, ' + chr(39) + '<([a-z][a-z0-9]*)' + chr(39) + ', 1)')} AS items, CAST(NULL AS BOOLEAN) AS label FROM pages",
    "conv_words": f"""WITH w AS (SELECT conv_id, role || '=' || unnest({_WORDS}) AS i FROM conversations), l AS (SELECT conv_id, bool_or(role = 'system') AS label FROM conversations GROUP BY 1)
SELECT conv_id AS tid, {_JOIN.format('list(i)')} AS items, any_value(label) AS label FROM w JOIN l USING (conv_id) GROUP BY conv_id""",
}


def joined(tx: DataFrame) -> DataFrame:
    return tx.withColumn("items", F.array_join("items", ","))
