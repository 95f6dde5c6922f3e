"""Forests from the given tables. Each function takes (spark, sf_dir) and returns vertices."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.encode import from_tokens, number, number_by_value

#: The total order of an order's items: (order, line) repeats, so all columns break ties.
ITEM_ORDER = ["l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]
#: Ranks of session events: an event's parent is the nearest earlier one of smaller rank; the session is 0.
EVENT_RANKS = {"signup": 1, "view": 2, "click": 3, "purchase": 4, "error": 5}
#: Elements without content, and those whose end tags are often left out: leaves under the flat policy.
VOID = ["area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"]
LEAVES = [*VOID, "p", "b"]


def _t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _items(spark: SparkSession, sf_dir: str) -> DataFrame:
    i = _t(spark, sf_dir, "lineitem")
    return i.withColumn("pos", F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*ITEM_ORDER)))


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order status / return flag / part type."""
    o, p = _t(spark, sf_dir, "orders"), _t(spark, sf_dir, "part").select("p_partkey", "p_type")
    i = _items(spark, sf_dir).select("l_orderkey", "pos", "l_returnflag", "l_partkey").join(o.select("o_orderkey"), F.col("l_orderkey") == F.col("o_orderkey"), "left_semi")
    root = o.select(F.col("o_orderkey").alias("tree_id"), F.lit(0).alias("pos"), F.lit(0).alias("level"), F.concat(F.lit("O:"), "o_orderstatus").alias("label"))
    line = i.select(F.col("l_orderkey").alias("tree_id"), "pos", F.lit(1).alias("level"), F.concat(F.lit("F:"), "l_returnflag").alias("label"))
    leaf = i.join(p, F.col("l_partkey") == F.col("p_partkey")).select(F.col("l_orderkey").alias("tree_id"), "pos", F.lit(2).alias("level"), F.concat(F.lit("T:"), "p_type").alias("label"))
    return number(root.union(line).union(leaf), ["pos", "level"], "level", [0, 1, 2])


def customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Market segment / order status / return flag and line status."""
    c, o, i = _t(spark, sf_dir, "customer"), _t(spark, sf_dir, "orders"), _items(spark, sf_dir)
    root = c.select(F.col("c_custkey").alias("tree_id"), F.lit(-1).cast("long").alias("o"), F.lit(0).alias("pos"), F.lit(0).alias("level"), F.concat(F.lit("C:"), "c_mktsegment").alias("label"))
    own = o.join(c.select("c_custkey"), F.col("o_custkey") == F.col("c_custkey"), "left_semi")
    order = own.select(F.col("o_custkey").alias("tree_id"), F.col("o_orderkey").alias("o"), F.lit(0).alias("pos"), F.lit(1).alias("level"), F.concat(F.lit("O:"), "o_orderstatus").alias("label"))
    item = i.join(own.select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("tree_id"), F.col("o_orderkey").alias("o"), "pos", F.lit(2).alias("level"), F.concat(F.lit("F:"), "l_returnflag", "l_linestatus").alias("label"))
    return number(root.union(order).union(item), ["o", "pos"], "level", [0, 1, 2])


def regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Region / nation / segment / order status: a few large trees."""
    r, n, c, o = (_t(spark, sf_dir, x) for x in ("region", "nation", "customer", "orders"))
    no = F.lit(-1).cast("long")
    n = n.join(F.broadcast(r.select("r_regionkey")), F.col("n_regionkey") == F.col("r_regionkey"), "left_semi")
    c = c.join(F.broadcast(n.select("n_nationkey", "n_regionkey")), F.col("c_nationkey") == F.col("n_nationkey"))
    o = o.join(c.select("c_custkey", "n_nationkey", "n_regionkey"), F.col("o_custkey") == F.col("c_custkey"))
    row = lambda df, tree, nation, cust, order, level, label: df.select(F.col(tree).cast("long").alias("tree_id"), nation.cast("long").alias("k1"), cust.cast("long").alias("k2"), order.cast("long").alias("k3"), F.lit(level).alias("level"), label.alias("label"))
    rows = row(r, "r_regionkey", no, no, no, 0, F.lit("R"))
    rows = rows.union(row(n, "n_regionkey", F.col("n_nationkey"), no, no, 1, F.lit("nation")))
    rows = rows.union(row(c, "n_regionkey", F.col("n_nationkey"), F.col("c_custkey"), no, 2, F.concat(F.lit("C:"), "c_mktsegment")))
    rows = rows.union(row(o, "n_regionkey", F.col("n_nationkey"), F.col("c_custkey"), F.col("o_orderkey"), 3, F.concat(F.lit("O:"), "o_orderstatus")))
    return number(rows, ["k1", "k2", "k3"], "level", [0, 1, 2, 3])


def library(spark: SparkSession, sf_dir: str) -> DataFrame:
    """customer / order / part type / brand: the digital-library shape."""
    c, o, p, i = _t(spark, sf_dir, "customer"), _t(spark, sf_dir, "orders"), _t(spark, sf_dir, "part"), _items(spark, sf_dir)
    own = o.join(c.select("c_custkey"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("o_orderkey", "o_custkey")
    item = i.select("l_orderkey", "pos", "l_partkey").join(own, F.col("l_orderkey") == F.col("o_orderkey")).join(p.select("p_partkey", "p_type", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    root = c.select(F.col("c_custkey").alias("tree_id"), F.lit(-1).cast("long").alias("o"), F.lit(0).alias("pos"), F.lit(0).alias("level"), F.lit("customer").alias("label"))
    order = own.select(F.col("o_custkey").alias("tree_id"), F.col("o_orderkey").alias("o"), F.lit(0).alias("pos"), F.lit(1).alias("level"), F.lit("order").alias("label"))
    kind = item.select(F.col("o_custkey").alias("tree_id"), F.col("o_orderkey").alias("o"), "pos", F.lit(2).alias("level"), F.concat(F.lit("T:"), "p_type").alias("label"))
    brand = item.select(F.col("o_custkey").alias("tree_id"), F.col("o_orderkey").alias("o"), "pos", F.lit(3).alias("level"), F.concat(F.lit("B:"), F.replace(F.col("p_brand"), F.lit("#"), F.lit(""))).alias("label"))
    return number(root.union(order).union(kind).union(brand), ["o", "pos", "level"], "level", [0, 1, 2, 3])


def day_stars(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A user's day as a star: a root a and a leaf b for each of its events."""
    i = day_chains(spark, sf_dir)
    leaf = i.select("tree_id", (F.col("lo") + 1).alias("lo"), (F.col("lo") + 1).alias("hi"), F.lit(1).alias("depth"), F.lit("b").alias("label"))
    return leaf.union(i.filter("lo = 0").select("tree_id", "lo", (F.col("hi") + 1).alias("hi"), F.lit(0).alias("depth"), F.lit("a").alias("label")))


def day_chains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events of a user's day as a chain of vertices a, each the child of the one before."""
    day = Window.partitionBy("tree_id")
    e = _t(spark, sf_dir, "events").filter("user_id is not null and ts is not null").select((F.col("user_id").cast("long") * 1_000_000 + F.unix_date(F.to_date("ts"))).alias("tree_id"), "event_id")
    e = e.select("tree_id", (F.row_number().over(day.orderBy("event_id")) - 1).alias("lo"), (F.count(F.lit(1)).over(day) - 1).cast("int").alias("hi"))
    return e.select("tree_id", "lo", "hi", F.col("lo").alias("depth"), F.lit("a").alias("label"))


def session_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with tree_id (the session's first event) of sessions of one user with gaps of at most 24 hours."""
    e = _t(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value")
    user = Window.partitionBy("user_id").orderBy("ts", "event_id")
    before = F.lag("ts").over(user)
    e = e.withColumn("first", F.when(before.isNull() | (F.col("ts") > before + F.expr("INTERVAL 24 HOURS")), F.col("event_id")))
    return e.withColumn("tree_id", F.last("first", ignorenulls=True).over(user.rowsBetween(Window.unboundedPreceding, Window.currentRow)))


def _sessions(e: DataFrame) -> DataFrame:
    root = e.filter("first is not null").select("tree_id", "ts", F.lit(-1).cast("long").alias("event_id"), F.lit("session").alias("label"), F.lit(float("inf")).alias("value"), F.lit(0).alias("rank"))
    rank = F.lit(max(EVENT_RANKS.values()) + 1)
    for name, r in EVENT_RANKS.items():
        rank = F.when(F.col("event_type") == name, r).otherwise(rank)
    return root.union(e.select("tree_id", "ts", "event_id", F.col("event_type").alias("label"), "value", rank.alias("rank")))


def sessions_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions; an event's parent is the nearest earlier event of smaller rank. No label repeats on a path."""
    return number(_sessions(session_events(spark, sf_dir)), ["ts", "event_id"], "rank", list(range(max(EVENT_RANKS.values()) + 2)), depth_is_rank=False)


def users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All of a user's events as one tree, by the parent rule of ranked sessions: labels repeat often below one root. tree_id is the user's first event."""
    e = session_events(spark, sf_dir).drop("first", "tree_id")
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = e.withColumn("tree_id", F.first("event_id").over(order)).withColumn("first", F.when(F.row_number().over(order) == 1, F.col("event_id")))
    return number(_sessions(whole), ["ts", "event_id"], "rank", list(range(max(EVENT_RANKS.values()) + 2)), depth_is_rank=False)


def sessions_value(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions; an event's parent is the nearest earlier event of larger value."""
    return number_by_value(_sessions(session_events(spark, sf_dir)), ["ts", "event_id"], "value")


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """conv / system and user turns / the assistant turns that follow them."""
    c = _t(spark, sf_dir, "conversations").select("conv_id", "turn", "role")
    root = c.select(F.col("conv_id").alias("tree_id")).distinct().select("tree_id", F.lit(-1).cast("long").alias("turn"), F.lit(0).alias("rank"), F.lit("conv").alias("label"))
    rows = root.union(c.select(F.col("conv_id").alias("tree_id"), "turn", F.when(F.col("role") == "assistant", 2).otherwise(1).alias("rank"), F.col("role").alias("label")))
    return number(rows, ["turn", "rank", "label"], "rank", [0, 1, 2], depth_is_rank=False)


def page_tokens(spark: SparkSession, sf_dir: str, policy: str = "flat") -> DataFrame:
    """Tags of pages as tokens. Comments and the content of script and style are no tags."""
    html = F.regexp_replace(F.lower("html"), r"(?s)<!--.*?-->", "")
    html = F.regexp_replace(html, r"(?s)(<script[^>]*>).*?(</script>)", "$1$2")
    html = F.regexp_replace(html, r"(?s)(<style[^>]*>).*?(</style>)", "$1$2")
    tags = _t(spark, sf_dir, "pages").select(F.col("page_id").alias("tree_id"), F.posexplode(F.regexp_extract_all(html, F.lit(r"</?[a-z][a-z0-9]*"), F.lit(0))).alias("pos", "tag"))
    t = tags.select("tree_id", "pos", F.regexp_replace("tag", "[</]", "").alias("label"), F.col("tag").startswith("</").alias("end"))
    leaves = LEAVES if policy == "flat" else VOID
    t = t.filter(~(F.col("end") & F.col("label").isin(leaves)))
    return t.select("tree_id", "pos", "label", F.when(F.col("end"), "close").when(F.col("label").isin(leaves), "leaf").otherwise("open").alias("kind"))


def pages_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """DOM trees; p, b and void elements are leaves."""
    return from_tokens(page_tokens(spark, sf_dir))


def outlines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Document by language / lines by length / sentences by length."""
    d = _t(spark, sf_dir, "documents").select(F.col("doc_id").alias("tree_id"), F.coalesce("text", F.lit("")).alias("text"), "lang")
    lines = d.select("tree_id", F.posexplode(F.split("text", "\n")).alias("i", "line"))
    n = F.length("line")
    line = lines.select("tree_id", "i", F.lit(-1).alias("j"), F.lit(1).alias("level"), F.concat(F.lit("line:"), F.when(n == 0, "empty").when(n < 40, "short").when(n < 200, "mid").otherwise("long")).alias("label"))
    sentences = lines.select("tree_id", "i", F.posexplode(F.split("line", r"\.")).alias("j", "s")).filter(F.trim("s") != "")
    m = F.length("s")
    sent = sentences.select("tree_id", "i", "j", F.lit(2).alias("level"), F.concat(F.lit("sent:"), F.when(m < 20, "short").when(m < 60, "mid").otherwise("long")).alias("label"))
    root = d.select("tree_id", F.lit(-1).alias("i"), F.lit(-1).alias("j"), F.lit(0).alias("level"), F.concat(F.lit("doc:"), "lang").alias("label"))
    return number(root.union(line).union(sent), ["i", "j"], "level", [0, 1, 2])


#: Host prefix, registered domain and first path segment of a page's URL.
_URL = r"^https?://(?:([^./]+)\.)?([^./]+\.example\.[a-z]+)/([^/?#]*)"


def urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One trie for each registered domain: site / host prefix / first path segment / page by kind. tree_id is the domain's least page_id."""
    p = _t(spark, sf_dir, "pages").select("page_id", "url").filter(F.col("url").rlike(_URL))
    part = lambda i: F.regexp_extract("url", _URL, i)
    kind = F.when(F.contains("url", F.lit("#")), "anchor").when(F.contains("url", F.lit("?")), "query").when(F.col("url").endswith(".html"), "html").when(F.col("url").endswith("/"), "slash").otherwise("plain")
    p = p.select("page_id", part(1).alias("host"), part(2).alias("domain"), part(3).alias("lang"), kind.alias("kind"))
    p = p.join(p.groupBy("domain").agg(F.min("page_id").alias("tree_id")), "domain")
    none, first = F.lit(""), F.lit(-1).cast("long")
    row = lambda host, lang, page, level, label: p.select("tree_id", host.alias("host"), lang.alias("lang"), page.alias("page"), F.lit(level).alias("level"), label.alias("label"))
    rows = row(none, none, first, 0, F.lit("site")).union(row(F.col("host"), none, first, 1, F.concat(F.lit("host:"), "host"))).union(row(F.col("host"), F.col("lang"), first, 2, F.concat(F.lit("lang:"), "lang"))).distinct()
    return number(rows.union(row(F.col("host"), F.col("lang"), F.col("page_id"), 3, F.concat(F.lit("page:"), "kind"))), ["host", "lang", "page", "level"], "level", [0, 1, 2, 3])


FORESTS = {"urls": urls, "orders": orders, "customers": customers, "regions": regions, "library": library, "sessions_rank": sessions_rank, "users": users, "sessions_value": sessions_value, "conversations": conversations, "pages_flat": pages_flat, "outlines": outlines}
