"""Graphs derived from the given tables, and generated ones.

Every derivation is a DataFrame plan over the columns it needs; ties are broken
by id, so two runs (and another engine) see one graph.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from hubloom.operators.graph import PropertyGraph
from hubloom.sources.tables import read_table


def part_flow(spark: SparkSession, sf_dir: str, m: int = 1, v_card: int = 10, e_card: int = 10) -> PropertyGraph:
    """Each part to the next higher part of an order (orders divisible by ``m``); acyclic."""
    lines = _order_parts(spark, sf_dir, m)
    nxt = Window.partitionBy("o").orderBy("p")
    steps = lines.select("o", F.col("p").alias("src"), F.lead("p").over(nxt).alias("tgt"), F.lead("q").over(nxt).alias("q")).where("tgt is not null")
    return PropertyGraph(_part_vertices(spark, sf_dir, v_card), _merged(steps, e_card), name=f"part_flow_{m}")


def part_flow_dense(spark: SparkSession, sf_dir: str, v_card: int = 10, e_card: int = 10) -> PropertyGraph:
    """Every ordered pair of parts of an order."""
    lines = _order_parts(spark, sf_dir, 1)
    a, b = lines.select("o", F.col("p").alias("src")), lines.select("o", F.col("p").alias("tgt"), "q")
    return PropertyGraph(_part_vertices(spark, sf_dir, v_card), _merged(a.join(b, "o").where("src < tgt"), e_card), name="part_flow_dense")


def _order_parts(spark: SparkSession, sf_dir: str, m: int) -> DataFrame:
    lines = read_table(spark, sf_dir, "lineitem").where(F.col("l_orderkey") % m == 0)
    return lines.groupBy(F.col("l_orderkey").alias("o"), F.col("l_partkey").alias("p")).agg(F.sum("l_quantity").cast("long").alias("q"))


def _part_vertices(spark: SparkSession, sf_dir: str, v_card: int) -> DataFrame:
    return read_table(spark, sf_dir, "part").select(
        F.col("p_partkey").alias("vid"), (F.col("p_partkey") % v_card).alias("v_grp"), F.col("p_size").cast("long").alias("v_mr"), "p_brand"
    )


def _merged(steps: DataFrame, e_card: int) -> DataFrame:
    return steps.groupBy("src", "tgt").agg((F.min("o") % e_card).alias("e_grp"), F.sum("q").alias("e_mr"), F.count("*").alias("n_steps"))


def order_chain(spark: SparkSession, sf_dir: str, v_card: int = 10) -> PropertyGraph:
    """Each order to the next higher order with the same part; edge groups are the six flag pairs."""
    flags = F.min(F.concat("l_returnflag", "l_linestatus"))
    lines = read_table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("o"), F.col("l_partkey").alias("p")).agg(F.sum("l_quantity").cast("long").alias("q"), flags.alias("f"))
    nxt = Window.partitionBy("p").orderBy("o")
    steps = lines.select(F.col("o").alias("src"), F.lead("o").over(nxt).alias("tgt"), F.lead("q").over(nxt).alias("q"), F.lead("f").over(nxt).alias("f")).where("tgt is not null")
    code = (F.instr(F.lit("ANR"), F.substring(F.min("f"), 1, 1)) - 1) * 2 + F.instr(F.lit("FO"), F.substring(F.min("f"), 2, 1)) - 1
    edges = steps.groupBy("src", "tgt").agg(code.cast("long").alias("e_grp"), F.sum("q").alias("e_mr"))
    vertices = read_table(spark, sf_dir, "orders").select(
        F.col("o_orderkey").alias("vid"), (F.col("o_orderkey") % v_card).alias("v_grp"), F.floor("o_totalprice").alias("v_mr"), "o_orderpriority"
    )
    return PropertyGraph(vertices, edges, name="order_chain")


def hand_offs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each event with the next one in time: ``(src, tgt, gap_us, event_type)``.

    Next rows are found inside days; the last event of a day meets the first of
    the next day that has any, so no task sorts the whole stream.
    """
    events = read_table(spark, sf_dir, "events").select(F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), "event_id", "user_id", "event_type")
    days = events.withColumn("day", F.floor(F.col("t") / 86_400_000_000))
    fields = ["t", "event_id", "user_id", "event_type"]
    # One row a day: small however many events there are.
    heads = days.groupBy("day").agg(F.min(F.struct(*fields)).alias("head"))
    by_day = Window.partitionBy(F.lit(0)).orderBy("day")
    following = heads.select("day", F.lead("head").over(by_day).alias("following"))
    inside = Window.partitionBy("day").orderBy("t", "event_id")
    nxt = days.select("day", "t", "user_id", F.lead(F.struct(*fields)).over(inside).alias("nxt"))
    both = nxt.join(F.broadcast(following), "day").withColumn("n", F.coalesce("nxt", "following")).where("n is not null")
    return both.select(F.col("user_id").alias("src"), F.col("n.user_id").alias("tgt"), (F.col("n.t") - F.col("t")).alias("gap_us"), F.col("n.event_type").alias("event_type")).where("src <> tgt")


def contact_graph(spark: SparkSession, sf_dir: str, max_gap_s: int | None = None, freq_scope: str = "kept") -> PropertyGraph:
    """User of an event to the user of the next, merged with frequency, main kind and closeness; cyclic.

    ``freq_scope="all"`` counts every hand-off of a pair that has one within the gap.
    """
    steps = hand_offs(spark, sf_dir)
    near = steps if max_gap_s is None else steps.where(F.col("gap_us") <= max_gap_s * 1_000_000)
    counted = steps if freq_scope == "all" else near
    kinds = counted.groupBy("src", "tgt", "event_type").agg(F.count("*").alias("n"))
    merged = kinds.groupBy("src", "tgt").agg(F.sum("n").alias("freq"), F.min(F.struct((-F.col("n")).alias("n"), "event_type")).alias("top"))
    if freq_scope == "all" and max_gap_s is not None:
        merged = merged.join(near.select("src", "tgt").distinct(), ["src", "tgt"], "left_semi")
    level = F.when(F.col("freq") >= 3, "HIGH").when(F.col("freq") == 2, "MIDDLE").otherwise("LOW")
    edges = merged.select("src", "tgt", "freq", F.col("top.event_type").alias("rel"), level.alias("closeness"), F.col("freq").alias("e_mr"), (F.col("freq") % 3).alias("e_grp"))
    events = read_table(spark, sf_dir, "events")
    users = events.groupBy(F.col("user_id").alias("vid")).agg(F.count("*").alias("n_events"), F.floor(F.sum(F.floor("value"))).alias("total_value"), F.min("ts").alias("first_ts"))
    vertices = users.withColumn("v_grp", F.col("vid") % 10).withColumn("v_mr", F.col("n_events"))
    return PropertyGraph(vertices, edges, name=f"contact_{max_gap_s}_{freq_scope}")


def mutual_contact(spark: SparkSession, sf_dir: str, max_gap_s: int | None = None) -> PropertyGraph:
    """The contacts that go both ways, as both arcs."""
    g = contact_graph(spark, sf_dir, max_gap_s)
    back = g.edges.select(F.col("tgt").alias("src"), F.col("src").alias("tgt"))
    return PropertyGraph(g.vertices, g.edges.join(back, ["src", "tgt"], "left_semi"), directed=False, name=f"mutual_{max_gap_s}")


LAYER = 1_000_000_000_000


def supply_layers(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """customer, order, part, supplier, nation, region as layers of one acyclic graph."""
    t = lambda n: read_table(spark, sf_dir, n)
    arc = lambda df, a, i, b, j: df.select((F.col(a) + F.lit(i * LAYER)).cast("long").alias("src"), (F.col(b) + F.lit(j * LAYER)).cast("long").alias("tgt"))
    lines = t("lineitem")
    edges = (
        arc(t("orders"), "o_custkey", 1, "o_orderkey", 2)
        .union(arc(lines, "l_orderkey", 2, "l_partkey", 3))
        .union(arc(lines, "l_partkey", 3, "l_suppkey", 4))
        .union(arc(t("supplier"), "s_suppkey", 4, "s_nationkey", 5))
        .union(arc(t("nation"), "n_nationkey", 5, "n_regionkey", 6))
        .groupBy("src", "tgt")
        .agg(F.count("*").alias("e_mr"))
        .withColumn("e_grp", F.expr(f"tgt div {LAYER}"))
    )
    parts = [("customer", "c_custkey", 1), ("orders", "o_orderkey", 2), ("part", "p_partkey", 3), ("supplier", "s_suppkey", 4), ("nation", "n_nationkey", 5), ("region", "r_regionkey", 6)]
    vertices = None
    for table, key, layer in parts:
        rows = t(table).select((F.col(key) + F.lit(layer * LAYER)).cast("long").alias("vid"), F.lit(layer).cast("long").alias("v_grp"), F.lit(1).cast("long").alias("v_mr"))
        vertices = rows if vertices is None else vertices.union(rows)
    return PropertyGraph(vertices, edges, name="supply_layers")


def dialogue_flow(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Turn to the next turn of a conversation."""
    turns = read_table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.char_length(F.coalesce("text", F.lit(""))).cast("long").alias("v_mr"))
    vid = F.col("conv_id") * 1000 + F.col("turn")
    vertices = turns.select(vid.alias("vid"), F.when(F.col("role") == "user", 0).otherwise(1).cast("long").alias("v_grp"), "v_mr", "role")
    nxt = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    edges = turns.select("conv_id", "turn", nxt.alias("nxt")).where("nxt is not null").select(vid.alias("src"), (F.col("conv_id") * 1000 + F.col("nxt")).alias("tgt"), F.lit(0).cast("long").alias("e_grp"), F.lit(1).cast("long").alias("e_mr"))
    return PropertyGraph(vertices, edges, name="dialogue_flow")


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(page_id, href, n)`` of every link in the pages."""
    links = read_table(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), 1)).alias("href"))
    return links.groupBy("page_id", "href").agg(F.count("*").alias("n"))


def word_succession(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(lang, a, b, n)``: word to following word over the documents of each language; large and cyclic."""
    words = F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != "")
    docs = read_table(spark, sf_dir, "documents").select("lang", words.alias("w"))
    pairs = docs.select("lang", F.explode(F.arrays_zip(F.slice("w", 1, F.greatest(F.size("w") - 1, F.lit(0))).alias("a"), F.slice("w", 2, F.greatest(F.size("w") - 1, F.lit(0))).alias("b"))).alias("p"))
    return pairs.groupBy("lang", "p.a", "p.b").agg(F.count("*").alias("n"))


def synthetic_dag(spark: SparkSession, n: int, degree: int, v_card: int = 10, e_card: int = 10, locality: float = 1.0, seed: int = 1, numbers: DataFrame | None = None) -> PropertyGraph:
    """A random acyclic graph: edges go from lower to higher ids, within a share ``locality`` of the id range.

    ``numbers(id)``: an edge is drawn for each of these in place of ``n * degree`` running numbers.
    """
    draw = lambda tag: F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}{tag}"), F.col("id").cast("string"))), 1, 8), 16, 10).cast("long")
    reach = max(1, int(n * locality))
    a = draw("a") % n
    other = draw("b") % n if locality >= 1 else (a + 1 + draw("b") % reach) % n
    drawn = (spark.range(n * degree) if numbers is None else numbers).select("id", a.alias("a"), other.alias("b")).where("a <> b")
    edges = drawn.groupBy(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("tgt")).agg((F.min("id") % e_card).alias("e_grp"), F.sum(F.col("id") % 100).alias("e_mr"))
    vertices = spark.range(n).select(F.col("id").alias("vid"), (F.col("id") % v_card).alias("v_grp"), (F.col("id") % 97).alias("v_mr"))
    return PropertyGraph(vertices, edges, name=f"dag_{n}_{degree}_{locality}_{seed}")


def worked_example(spark: SparkSession) -> PropertyGraph:
    """Five hubs 1..5 and six inner vertices: 11 = A1, 21, 22 = B1, B2, 31..33 = C1..C3."""
    arcs = [(1, 11), (11, 2), (2, 21), (2, 22), (21, 3), (22, 3), (3, 31), (3, 32), (31, 33), (32, 4), (32, 5), (33, 4), (33, 5)]
    vids = sorted({v for arc in arcs for v in arc})
    vertices = spark.createDataFrame([(v, v % 2, v) for v in vids], "vid long, v_grp long, v_mr long")
    edges = spark.createDataFrame([(s, t, t % 2, s + t) for s, t in arcs], "src long, tgt long, e_grp long, e_mr long")
    return PropertyGraph(vertices, edges, name="worked")
