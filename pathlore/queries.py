"""Registered queries of the graph engine, each with SQL where SQL can say it."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from pathlore import experiments, workload
from pathlore.functions import paths
from pathlore.operators import chase, closure, consistency, staging, statistics, temporal
from pathlore.operators.certain import certain_answers, certain_answers_of_parts, plain_answers
from pathlore.operators.evaluate import Evaluator, answer
from pathlore.operators.runtime_jumps import answer_with_runtime_jumps
from pathlore.oracle import tables
from pathlore.plans.ontology import parse_ontology, shop
from pathlore.plans.query import parse_query
from pathlore.plans.render import to_sql
from pathlore.plans.rewrite import rewrite
from pathlore.sources.graph import KEY_BITS, KINDS, build_graph, natural_key, table
from pathlore.streaming import events as event_stream

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return put


# ---- the workloads -----------------------------------------------------------------------------------------------------

BULK = "SELECT l_orderkey, l_partkey, l_suppkey FROM lineitem WHERE l_quantity >= 45 AND l_discount >= 0.08"
WORKLOAD_SQL = {
    "w1_cobuyer_star": f"""
        WITH RECURSIVE step(a, b) AS (
            SELECT DISTINCT o1.o_custkey, o2.o_custkey
            FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem WHERE l_quantity >= 49) h JOIN orders o1 ON h.l_orderkey = o1.o_orderkey
            JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) i ON h.l_partkey = i.l_partkey JOIN orders o2 ON i.l_orderkey = o2.o_orderkey),
        reach(x, c) AS (SELECT c_custkey, c_custkey FROM customer WHERE c_acctbal >= 9900 UNION SELECT x, b FROM reach JOIN step ON c = a)
        SELECT DISTINCT x, o_orderkey AS y FROM reach JOIN orders ON o_custkey = c WHERE o_orderkey IN (SELECT l_orderkey FROM ({BULK}))""",
    "w2_part_to_error_customer": """
        SELECT DISTINCT l_partkey AS x, c_custkey AS y FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
        WHERE l_quantity >= 50 AND c_acctbal >= 5000 AND c_custkey IN (SELECT user_id FROM events WHERE event_type = 'error')""",
    "w3_reply_chain": """
        WITH RECURSIVE nxt AS (SELECT conv_id, turn, lead(turn) OVER w AS n, lead(length(text)) OVER w AS chars FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)),
        walk(c, s, t) AS (SELECT conv_id, turn, turn FROM conversations WHERE turn = 0 UNION SELECT c, s, n FROM walk JOIN nxt ON c = conv_id AND t = turn WHERE n IS NOT NULL AND chars >= 50)
        SELECT DISTINCT c * 256 + s AS x, c * 256 + t AS y FROM walk""",
    "w4_local_supplier": """
        SELECT DISTINCT o_custkey AS x, l_suppkey AS y FROM orders JOIN lineitem ON l_orderkey = o_orderkey
        JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_nationkey = s_nationkey""",
    "v1_licensed": "SELECT s_suppkey AS x FROM supplier WHERE s_acctbal >= 5000",
    "v2_accredited_region": "SELECT s_suppkey AS x, n_regionkey AS y FROM supplier JOIN nation ON s_nationkey = n_nationkey",
    "v3_handled_supplier": f"SELECT DISTINCT o_custkey AS x FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM ({BULK}))",
    "v4_tracked_brand": f"""
        SELECT DISTINCT l_orderkey AS x, p_brand AS y FROM lineitem JOIN part ON l_partkey = p_partkey
        WHERE l_orderkey IN (SELECT l_orderkey FROM ({BULK})) AND l_partkey IN (SELECT l_partkey FROM ({BULK}))""",
    "v5_licence_star": f"SELECT DISTINCT l_suppkey AS x, l_orderkey AS y FROM lineitem WHERE l_orderkey IN (SELECT l_orderkey FROM ({BULK}))",
}


def workload_query(name: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = build_graph(spark, sf_dir, workload.VIEWS.get(name, ("commerce",)))
        if name != "v4_tracked_brand":
            return certain_answers(workload.QUERIES[name], g, shop())
        pairs = certain_answers(workload.QUERIES[name], g, shop(), decode=False)
        return pairs.join(g.kinds["brand"].rows, pairs.y == F.col("node_id")).select(natural_key("x").alias("x"), F.col("name").alias("y"))

    return run


for _name in workload.QUERIES:
    query(WORKLOAD_SQL[_name], _name)(workload_query(_name))


#: Answers of the workload without the ontology, where there are any: the data have no edge or label of an implied name.
PLAIN_SQL = {"w3_reply_chain": WORKLOAD_SQL["w3_reply_chain"]}


@query(" UNION ALL ".join(f"SELECT '{n}' AS query, {f'(SELECT count(*) FROM ({PLAIN_SQL[n]}))' if n in PLAIN_SQL else 'CAST(0 AS BIGINT)'} AS plain, (SELECT count(*) FROM ({sql})) AS certain" for n, sql in WORKLOAD_SQL.items()))
def plain_vs_rewritten_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Answers of every hand-written query with and without the ontology, counted one after the other; what one has written is given back before the next."""
    out = []
    g = build_graph(spark, sf_dir, ("commerce", "activity"))
    for name, text in workload.QUERIES.items():
        counts = []
        for answers in (lambda: plain_answers(text, g), lambda: certain_answers(text, g, shop())):  # called at once
            with staging.scratch():
                counts.append(answers().count())
        out.append((name, *counts))
    return spark.createDataFrame(out, "query string, plain long, certain long")


@query(WORKLOAD_SQL["w4_local_supplier"])
def w4_on_core_chase(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The baseline that materialises implied facts and then evaluates the query as it is."""
    return plain_answers(workload.QUERIES["w4_local_supplier"], chase.core_chase(build_graph(spark, sf_dir, ("commerce",)), shop()))


@query(WORKLOAD_SQL["v3_handled_supplier"])
def v3_on_bounded_chase(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same with unseen nodes, one edge deep."""
    return plain_answers(workload.QUERIES["v3_handled_supplier"], chase.bounded_chase(build_graph(spark, sf_dir, ("commerce",)), shop(), 1))


def jumping(name: str) -> Query:
    return lambda spark, sf_dir: answer_with_runtime_jumps(parse_query(workload.QUERIES[name]), build_graph(spark, sf_dir, ("commerce",)), shop())


for _name in ("v1_licensed", "v2_accredited_region", "v3_handled_supplier", "v5_licence_star"):
    query(WORKLOAD_SQL[_name], f"{_name}_runtime_jumps")(jumping(_name))


# ---- rules and rewriting variants ---------------------------------------------------------------------------------------


def pairs_query(text: str, views: tuple[str, ...] = ("commerce",), **how) -> Query:
    return lambda spark, sf_dir: certain_answers(text, build_graph(spark, sf_dir, views), shop(), **how)


RPQS: dict[str, tuple[Query, str]] = {
    "rpq_concat": (pairs_query("ans(x,y) <- customerNation/inRegion(x,y)"), "SELECT c_custkey AS x, n_regionkey AS y FROM customer JOIN nation ON c_nationkey = n_nationkey"),
    "rpq_union": (
        pairs_query("ans(x,y) <- :Party/(customerNation|placed/:OpenOrder)(x,y)"),
        "SELECT c_custkey AS x, c_nationkey AS y FROM customer UNION SELECT o_custkey, o_orderkey FROM orders WHERE o_orderstatus = 'O'",
    ),
    "rpq_star": (
        pairs_query("ans(x,y) <- [turn=0]/nextTurn*(x,y)", ("activity",)),
        "SELECT a.conv_id * 256 AS x, b.conv_id * 256 + b.turn AS y FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id WHERE a.turn = 0",
    ),
    "rpq_inverse": (pairs_query("ans(x,y) <- :Nation/^customerNation/[acctbal<=0](x,y)"), "SELECT c_nationkey AS x, c_custkey AS y FROM customer WHERE c_acctbal <= 0"),
    "rpq_nested": (
        pairs_query("ans(x,y) <- :Customer/<placed/{hasItem,quantity>=50}>/customerNation(x,y)"),
        "SELECT c_custkey AS x, c_nationkey AS y FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_quantity >= 50)",
    ),
    "rpq_optional": (
        pairs_query("ans(x,y) <- :Supplier/supplierNation/inRegion?(x,y)"),
        "SELECT s_suppkey AS x, s_nationkey AS y FROM supplier UNION SELECT s_suppkey, n_regionkey FROM supplier JOIN nation ON s_nationkey = n_nationkey",
    ),
    "rpq_plus": (
        pairs_query("ans(x,y) <- [turn=0]/nextTurn+(x,y)", ("activity",)),
        "SELECT a.conv_id * 256 AS x, b.conv_id * 256 + b.turn AS y FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id WHERE a.turn = 0 AND b.turn > 0",
    ),
    "edge_set_edge": (
        pairs_query("ans(x,y) <- {hasItem,quantity>=40,discount<=0.01}(x,y)"),
        "SELECT DISTINCT l_orderkey AS x, l_partkey AS y FROM lineitem WHERE l_quantity >= 40 AND l_discount <= 0.01",
    ),
    "edge_set_pair": (
        lambda spark, sf_dir: plain_answers("ans(x,y) <- {hasItem,quantity>=40,discount<=0.01}(x,y)", build_graph(spark, sf_dir, ("commerce",)), binding="pair"),
        """SELECT l_orderkey AS x, l_partkey AS y FROM lineitem WHERE l_quantity >= 40
           INTERSECT SELECT l_orderkey, l_partkey FROM lineitem WHERE l_discount <= 0.01""",
    ),
    "closing_atom": (pairs_query("ans(x) <- :Customer/(placed/^placed)(x,x)"), "SELECT DISTINCT o_custkey AS x FROM orders"),
    "unanswered_left": (
        pairs_query("ans(y) <- [acctbal>=9000]/placed/{hasItem,quantity>=50}(z,y)"),
        "SELECT DISTINCT l_partkey AS y FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey WHERE l_quantity >= 50 AND c_acctbal >= 9000",
    ),
    "star_under_plain_ontology": (
        pairs_query("ans(x,y) <- [turn=0]/(nextTurn/:Turn)*(x,y)", ("activity",)),
        "SELECT a.conv_id * 256 AS x, b.conv_id * 256 + b.turn AS y FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id WHERE a.turn = 0",
    ),
}
for _name, (_run, _sql) in RPQS.items():
    query(_sql, _name)(_run)


@query("SELECT DISTINCT o_custkey AS x, l_partkey AS y FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_nationkey = 3)")
def bound_endpoint(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A variable restricted to given nodes seeds the evaluation."""
    g = build_graph(spark, sf_dir, ("commerce",))
    start = g.roles["customerNation"].where(natural_key("dst") == 3).select(F.col("src").alias("node_id"))
    return answer(rewrite(parse_query("ans(x,y) <- placed/hasItem(x,y)"), shop()).query, g, bindings={"x": start})


@query(f"SELECT DISTINCT l_orderkey AS x, l_partkey AS y FROM ({BULK})")
def bulk_deal_role(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A role that only edge tests imply."""
    return certain_answers("ans(x,y) <- deal(x,y)", build_graph(spark, sf_dir, ("commerce",)), shop())


@query("SELECT 3 AS kind, c_custkey AS key FROM customer WHERE c_acctbal >= 9000 UNION ALL SELECT 4, s_suppkey FROM supplier WHERE s_acctbal >= 9000")
def wealthy_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A label that node tests imply, over two kinds of nodes."""
    rows = certain_answers("ans(x) <- :Wealthy(x)", build_graph(spark, sf_dir, ("commerce",)), shop(), decode=False)
    return rows.select(F.shiftright("x", KEY_BITS).cast("int").alias("kind"), natural_key("x").alias("key"))


@query("SELECT doc_id FROM documents JOIN labels USING (doc_id) WHERE quality = 1 AND toxic = 0")
def clean_text_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Properties that only some nodes have."""
    return certain_answers("ans(x) <- :CleanText(x)", build_graph(spark, sf_dir, ("text",)), shop()).withColumnRenamed("x", "doc_id")


@query("SELECT doc_id, first AS class_id FROM (SELECT doc_id, min(doc_id) OVER w AS first, count(*) OVER w AS n FROM documents WINDOW w AS (PARTITION BY text)) WHERE n > 1")
def symmetric_same_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The star of a symmetric role, kept factorised: each node with the representative of its class."""
    onto = parse_ontology("role firstCopy < sameText\nrole sameText < ^sameText")
    star = certain_answers("ans(x,y) <- <^sameText>/^sameText(x,y)", build_graph(spark, sf_dir, ("text",)), onto)
    first = star.groupBy("x").agg(F.min("y").alias("m"))
    return first.select(F.col("x").alias("doc_id"), F.least("x", "m").alias("class_id"))


@query("SELECT user_id, count(*) * (count(*) - 1) // 2 AS n_pairs FROM events GROUP BY user_id")
def next_event_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of the strict closure of a chain role, from positions, without iteration."""
    placed = temporal.chain_positions(table(spark, sf_dir, "events").select("user_id", "ts", "event_id"), "user_id", "ts", "event_id")
    return placed.groupBy("user_id").agg(F.sum(F.col("position") - 1).alias("n_pairs"))


@query("SELECT a.conv_id * 256 + a.turn AS x, b.conv_id * 256 + b.turn AS y FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND a.turn >= b.turn")
def next_turn_star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The star of an implied inverse role, by iteration over the automaton."""
    return certain_answers("ans(x,y) <- :Turn/follows*(x,y)", build_graph(spark, sf_dir, ("activity",)), shop())


# ---- materialisation, consistency, statistics ----------------------------------------------------------------------------


@query(
    """SELECT role, count(*) AS n FROM (
        SELECT DISTINCT 'itemOf' AS role, l_partkey AS s, l_orderkey AS d, 0 AS k FROM lineitem
        UNION ALL SELECT DISTINCT 'deal', l_orderkey, l_partkey, 0 FROM lineitem WHERE l_quantity >= 45 AND l_discount >= 0.08
        UNION ALL SELECT 'locatedIn', c_custkey, c_nationkey, 3 FROM customer UNION ALL SELECT 'locatedIn', s_suppkey, s_nationkey, 4 FROM supplier UNION ALL SELECT 'locatedIn', n_nationkey, n_regionkey, 2 FROM nation
        UNION ALL SELECT 'involvedIn', o_custkey, o_orderkey, 3 FROM orders UNION ALL SELECT DISTINCT 'involvedIn', l_suppkey, l_orderkey, 4 FROM lineitem) GROUP BY role"""
)
def core_chase_roles(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = chase.core_chase(build_graph(spark, sf_dir, ("commerce",)), shop())
    rows = [g.roles[r].select(F.lit(r).alias("role"), "src", "dst") for r in ("locatedIn", "involvedIn", "itemOf", "deal")]
    return reduce(DataFrame.unionByName, rows).groupBy("role").agg(F.count("*").alias("n"))


@query(
    f"""SELECT 'Buyer' AS label, (SELECT count(DISTINCT o_custkey) FROM orders) AS n
        UNION ALL SELECT 'Party', (SELECT count(*) FROM customer) + (SELECT count(*) FROM supplier)
        UNION ALL SELECT 'Organisation', (SELECT count(*) FROM supplier)
        UNION ALL SELECT 'BigOrder', (SELECT count(*) FROM orders WHERE o_totalprice >= 400000)
        UNION ALL SELECT 'BulkOrder', (SELECT count(DISTINCT l_orderkey) FROM ({BULK}))
        UNION ALL SELECT 'BulkPart', (SELECT count(DISTINCT l_partkey) FROM ({BULK}))"""
)
def core_chase_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = build_graph(spark, sf_dir, ("commerce",))
    names = ("Buyer", "Party", "Organisation", "BigOrder", "BulkOrder", "BulkPart")
    found = {n: chase.implied_nodes(g, shop(), n) for n in names}
    return reduce(DataFrame.unionByName, [rows.agg(F.count("*").alias("n")).select(F.lit(n).alias("label"), "n") for n, rows in found.items()])


@query(
    """SELECT 'Buyer disjoint Overdrawn' AS axiom, c_custkey AS node FROM customer WHERE c_acctbal <= 0 AND c_custkey IN (SELECT o_custkey FROM orders)
       UNION ALL SELECT 'Organisation disjoint Wealthy', s_suppkey FROM supplier WHERE s_acctbal >= 9000"""
)
def violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nodes that break negative axioms put on top of the ontology."""
    onto = shop()
    onto.concepts += parse_ontology("disjoint concept Buyer, Overdrawn\ndisjoint concept Organisation, Wealthy").concepts
    return consistency.violations(build_graph(spark, sf_dir, ("commerce",)), onto).select("axiom", natural_key("node").alias("node"))


@query(
    """SELECT 'customerNation' AS role, count(*) AS n_edges, count(DISTINCT c_custkey) AS n_src, count(DISTINCT c_nationkey) AS n_dst FROM customer
       UNION ALL SELECT 'supplierNation', count(*), count(DISTINCT s_suppkey), count(DISTINCT s_nationkey) FROM supplier
       UNION ALL SELECT 'inRegion', count(*), count(DISTINCT n_nationkey), count(DISTINCT n_regionkey) FROM nation
       UNION ALL SELECT 'placed', count(*), count(DISTINCT o_custkey), count(DISTINCT o_orderkey) FROM orders
       UNION ALL SELECT 'hasItem', count(*), count(DISTINCT l_orderkey), count(DISTINCT l_partkey) FROM lineitem
       UNION ALL SELECT 'shippedBy', count(*), count(DISTINCT l_orderkey), count(DISTINCT l_suppkey) FROM lineitem
       UNION ALL SELECT 'supplies', count(*), count(DISTINCT l_suppkey), count(DISTINCT l_partkey) FROM (SELECT DISTINCT l_suppkey, l_partkey FROM lineitem)
       UNION ALL SELECT 'ofBrand', count(*), count(DISTINCT p_partkey), count(DISTINCT p_brand) FROM part"""
)
def graph_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return statistics.role_statistics(build_graph(spark, sf_dir, ("commerce",)))


@query(
    """SELECT c_custkey AS key, CASE WHEN c_custkey IN (SELECT o_custkey FROM orders) THEN 'customerNation,placed' ELSE 'customerNation' END AS out_roles FROM customer"""
)
def node_signature(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Signatures of the customers."""
    rows = statistics.node_signature(build_graph(spark, sf_dir, ("commerce",)))
    return rows.where(F.shiftright("node_id", KEY_BITS) == 3).select(natural_key("node_id").alias("key"), F.array_join("out_roles", ",").alias("out_roles"))


@query("SELECT n_regionkey, c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, c_mktsegment)")
def rollup_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    nation = table(spark, sf_dir, "nation")
    return table(spark, sf_dir, "customer").join(nation, F.col("c_nationkey") == F.col("n_nationkey")).rollup("n_regionkey", "c_mktsegment").agg(F.count("*").alias("n"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def cube_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"))


@query("SELECT l_partkey AS part, count(*) AS n FROM lineitem GROUP BY l_partkey ORDER BY n DESC, part LIMIT 10")
def top_hubs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten parts with most order lines (a top-k report)."""
    g = build_graph(spark, sf_dir, ("commerce",))
    return g.roles["hasItem"].groupBy("dst").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "dst").limit(10).select(natural_key("dst").alias("part"), "n")


@query("SELECT o_orderkey, p_partkey FROM (SELECT l_orderkey AS o_orderkey, l_partkey AS p_partkey, count(*) AS n FROM lineitem GROUP BY ALL) WHERE n > 1")
def parallel_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs that one role joins more than once."""
    from pathlore.sources.graph import strict_single_edge

    g = build_graph(spark, sf_dir, ("commerce",))
    rows = strict_single_edge(g.roles["hasItem"].select(F.lit("hasItem").alias("role"), "src", "dst"))
    return rows.select(natural_key("src").alias("o_orderkey"), natural_key("dst").alias("p_partkey"))


@query(
    " UNION ALL ".join(
        f"SELECT '{kind}' AS kind, count({what}) AS n_nodes FROM {name}"
        for kind, what, name in (
            ("region", "*", "region"), ("nation", "*", "nation"), ("customer", "*", "customer"), ("supplier", "*", "supplier"), ("part", "*", "part"), ("order", "*", "orders"), ("brand", "DISTINCT p_brand", "part"),
            ("event", "*", "events"), ("turn", "*", "conversations"), ("conversation", "DISTINCT conv_id", "conversations"), ("document", "*", "documents"), ("source", "DISTINCT source", "documents"), ("lang", "DISTINCT lang", "documents"),
            ("page", "*", "pages"), ("host", "DISTINCT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1)", "pages"),
            ("target", "DISTINCT href", """(SELECT unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)"""),
        )
    )
)
def data_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nodes of each kind, over all views."""
    return statistics.node_counts(build_graph(spark, sf_dir))


@query("SELECT DISTINCT o_custkey AS x FROM orders")
def existence_by_signature(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A concept that an edge's existence implies, as a filter on the node signature."""
    g = build_graph(spark, sf_dir, ("commerce",))
    q = rewrite(parse_query("ans(x) <- :Buyer(x)"), shop()).query
    return answer(q, g, evaluator=Evaluator(g, q.book.copy(), signature=statistics.node_signature(g)))


@query("SELECT a.conv_id * 256 + a.turn AS x, b.conv_id * 256 + b.turn AS y FROM conversations a JOIN conversations b USING (conv_id)")
def packed_states(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A star over two states that are iterated, kept as bits of one row a pair."""
    g = build_graph(spark, sf_dir, ("activity",))
    q = rewrite(parse_query("ans(x,y) <- :Turn/(nextTurn|^nextTurn)*(x,y)"), shop()).query
    return answer(q, g, evaluator=Evaluator(g, q.book.copy(), packed=True))


def talk_tables(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """The turns of conversations as open tables of nodes and edges."""
    g = build_graph(spark, sf_dir, ("activity",))
    turns, talks = g.kinds["turn"].rows, g.kinds["conversation"].rows
    nodes = turns.select("node_id", F.array(F.lit("Turn")).alias("labels"), "turn").unionByName(talks.select("node_id", F.array(F.lit("Conversation")).alias("labels"), F.lit(None).cast("bigint").alias("turn")))
    edges = g.roles["nextTurn"].select(F.lit("nextTurn").alias("role"), "src", "dst", "reply_chars").unionByName(g.roles["inConversation"].select(F.lit("inConversation").alias("role"), "src", "dst", F.lit(None).cast("int").alias("reply_chars")))
    return nodes, edges


@query(WORKLOAD_SQL["w3_reply_chain"])
def w3_recursive_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rewritten query as SQL with a recursive common table expression, which ends as turns make no cycle.

    Spark's own limits hold: 100 levels, and as many rows as spark.sql.cteRecursionRowLimit allows.
    """
    names = [f"w3_{kind}_{uuid.uuid4().hex}" for kind in ("nodes", "edges")]
    for name, rows in zip(names, talk_tables(spark, sf_dir), strict=True):
        rows.createOrReplaceTempView(name)
    q = rewrite(parse_query(workload.QUERIES["w3_reply_chain"]), shop()).query
    found = spark.sql(to_sql(q, acyclic_data=True, nodes=names[0], edges=names[1]))
    return found.select(*(natural_key(v).alias(v) for v in q.answer))


@query(WORKLOAD_SQL["w3_reply_chain"])
def w3_by_component(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by run search in Python, a task a conversation."""
    nodes, edges = talk_tables(spark, sf_dir)
    q = rewrite(parse_query(workload.QUERIES["w3_reply_chain"]), shop()).query
    kinds = F.shiftright("node_id", KEY_BITS)
    talk = F.when(kinds == KINDS["turn"], F.shiftright(natural_key("node_id"), 8)).otherwise(natural_key("node_id"))
    own = edges.withColumn("talk", F.shiftright(natural_key("src"), 8))
    return paths.run_components(nodes.withColumn("talk", talk), own, "talk", q).select(*(natural_key(v).alias(v) for v in q.answer))


@query(
    """SELECT user_id, automaton, from_state, CASE symbol WHEN 'r' THEN r WHEN 's' THEN s WHEN '^t' THEN '^' || t ELSE symbol END AS symbol, to_state
       FROM (SELECT user_id, arg_min(event_type, event_id) AS r, arg_max(event_type, event_id) AS s, min(event_type) AS t FROM events GROUP BY user_id),
            (VALUES (0, 0, 'r', 1), (0, 1, 's', 2), (0, 1, '<1>', 3), (0, 2, 's', 2), (0, 2, '<1>', 3), (0, 3, 's', 2), (0, 3, '<1>', 3), (1, 0, '^t', 1)) AS m(automaton, from_state, symbol, to_state)"""
)
def path_moves(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The moves of a path expression's automata, by a table function: for each user one of the first, the last and the least kind of event."""
    kinds = table(spark, sf_dir, "events").groupBy("user_id").agg(F.min_by("event_type", "event_id").alias("r"), F.max_by("event_type", "event_id").alias("s"), F.min("event_type").alias("t"))
    texts = kinds.select("user_id", F.format_string("%s/(%s|<^%s>)*", "r", "s", "t").alias("path"))
    return texts.lateralJoin(paths.path_symbols(F.col("path").outer())).select("user_id", "automaton", "from_state", "symbol", "to_state")


@query("SELECT r_regionkey AS x, n_nationkey AS y FROM region, nation WHERE n_regionkey <= 1")
def unconnected_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A query of two parts that share no variable: a product, asked for."""
    g = build_graph(spark, sf_dir, ("commerce",))
    few = g.roles["inRegion"].where(natural_key("dst") <= 1).select(F.col("src").alias("node_id"))
    return certain_answers_of_parts("ans(x,y) <- :Region(x) & :Nation(y)", g, shop(), allow_product=True, bindings={"y": few})


@query(
    """SELECT c_nationkey, c_custkey, rank() OVER w AS place, dense_rank() OVER w AS level, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY n DESC, c_custkey) AS quarter,
              CAST(count(*) OVER (PARTITION BY c_nationkey ORDER BY n RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS BIGINT) AS near
       FROM (SELECT c_nationkey, c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1, 2)
       WINDOW w AS (PARTITION BY c_nationkey ORDER BY n DESC)"""
)
def ranked_answers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers of each nation by the number of their orders: ranks, quarters, and how many are within two orders."""
    rows = table(spark, sf_dir, "customer").join(table(spark, sf_dir, "orders"), F.col("o_custkey") == F.col("c_custkey"), "left")
    rows = rows.groupBy("c_nationkey", "c_custkey").agg(F.count("o_orderkey").alias("n"))
    of = W.partitionBy("c_nationkey")
    down = of.orderBy(F.desc("n"))
    return rows.select(
        "c_nationkey", "c_custkey", F.rank().over(down).alias("place"), F.dense_rank().over(down).alias("level"), F.ntile(4).over(of.orderBy(F.desc("n"), "c_custkey")).alias("quarter"), F.count("*").over(of.orderBy("n").rangeBetween(-2, 2)).alias("near")
    )


@query("SELECT a.user_id, a.event_id, b.event_id AS next_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def purchase_after_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The interval join that also runs between two streams, on the batch."""
    return event_stream.followed_by(table(spark, sf_dir, "events"), "view", "purchase", "6 hours")


# ---- surrounding operators -----------------------------------------------------------------------------------------------


@query("SELECT a.user_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY a.user_id")
def interval_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return temporal.interval_pairs(table(spark, sf_dir, "events"), "user_id", "ts", "event_id", 3600).groupBy("user_id").agg(F.count("*").alias("n"))


@query(
    """SELECT e.event_id, p.event_id AS purchase_id FROM (SELECT * FROM events WHERE event_type = 'error') e
       ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p ON e.user_id = p.user_id AND e.ts >= p.ts"""
)
def asof_last_event(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last purchase of the same user before each error."""
    events = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    errors = events.where("event_type = 'error'").select("event_id", "user_id", "ts")
    bought = events.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("bought_at"), F.col("event_id").alias("purchase_id"))
    return temporal.asof_join(errors, bought, "user_id", "ts", "bought_at", "purchase_id").select("event_id", "purchase_id")


@query("SELECT o_custkey AS x FROM orders WHERE o_totalprice >= 400000 INTERSECT SELECT user_id FROM events EXCEPT SELECT c_custkey FROM customer WHERE c_acctbal <= 0")
def set_ops(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Answers of unary queries under intersection and difference."""
    g = build_graph(spark, sf_dir, ("commerce", "activity"))
    one = lambda text: certain_answers(text, g, shop())
    return one("ans(x) <- placed/:BigOrder(x,w)").intersect(one("ans(x) <- performed(x,w)")).exceptAll(one("ans(x) <- :Customer/:Overdrawn(x)")).distinct()


@query("SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def json_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Open properties read out of JSON."""
    return build_graph(spark, sf_dir, ("activity",)).kinds["event"].rows.groupBy("k").agg(F.count("*").alias("n"))


@query("""SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages""")
def href_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))


CONCEPT_SQL = "SELECT *, unnest(CASE WHEN event_type IN ('view', 'click', 'purchase') THEN ['Interaction', 'Activity'] WHEN event_type = 'signup' THEN ['Activity'] ELSE [] END) AS concept FROM events"


def shown(rows: DataFrame, column: str) -> DataFrame:
    return rows.withColumn(column, F.date_format(column, "yyyy-MM-dd HH:mm:ss"))


@query(f"SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS window_start, concept, count(*) AS n FROM ({CONCEPT_SQL}) GROUP BY 1, 2")
def concept_window_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(event_stream.tumbling(table(spark, sf_dir, "events"), shop()).drop("total"), "window_start")


@query(
    f"""SELECT strftime(d, '%Y-%m-%d %H:%M:%S') AS window_start, concept, count(*) AS n
        FROM (SELECT *, unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS d FROM ({CONCEPT_SQL})) GROUP BY 1, 2"""
)
def concept_window_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(event_stream.sliding(table(spark, sf_dir, "events"), shop()), "window_start")


@query(
    f"""WITH a AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM ({CONCEPT_SQL}) WHERE concept = 'Activity' WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
        b AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM a)
        SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS session_start, count(*) AS n FROM b GROUP BY user_id, s"""
)
def concept_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(event_stream.sessions(table(spark, sf_dir, "events"), shop(), "6 hours"), "session_start")


# ---- cost measures of the rewriting, over ontologies with the classes that the tables name ---------------------------------------------------------------------

STATS = "query string, states_in int, states_out int, transitions_in int, transitions_out int, tuples_minimal int, infeasible boolean, rewrite_ms double, candidates_all string, candidates_relevant string"


def names_in(spark: SparkSession, sf_dir: str) -> tuple[tuple[str, str], ...]:
    return tuple(workload.table_names(spark, sf_dir))


@query()
def rewrite_stats_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """100 random queries over the large ontology without existentials."""
    onto = experiments.ontologies(names_in(spark, sf_dir))["flat"]
    return spark.createDataFrame(list(workload.rewriting_stats(onto, workload.generate_queries(onto))), STATS)


@query()
def rewrite_stats_shop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """100 random queries over the small ontology with existentials."""
    onto = experiments.ontologies(names_in(spark, sf_dir))["shop"]
    return spark.createDataFrame(list(workload.rewriting_stats(onto, workload.generate_queries(onto))), STATS)


@query()
def skip_tuples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The minimal jumps of the queries over existentials."""
    rows = []
    for name in sorted(workload.QUERIES):
        found = rewrite(parse_query(workload.QUERIES[name]), shop()).tuples
        rows += [(name, n, t.concept, t.state, str(t.target), str(sorted(t.rest))) for n, ts in found.items() for t in ts]
    return spark.createDataFrame(rows, "query string, automaton int, concept string, state int, target string, rest string")


@query()
def candidate_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the exhaustive and the relevance-pruned ways would have to check, against the minimal tuples found."""
    rows, onto = [], workload.with_names(shop(), names_in(spark, sf_dir))
    for name in sorted(workload.QUERIES):
        s = rewrite(parse_query(workload.QUERIES[name]), onto).stats
        rows.append((name, str(s.candidates_all), str(s.candidates_relevant), s.tuples_minimal))
    return spark.createDataFrame(rows, "query string, candidates_all string, candidates_relevant string, tuples_minimal int")


@query()
def baseline_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every way of finding jumps over every hand-written query: candidates, jumps, whether it is infeasible, and the time."""
    return spark.createDataFrame(list(experiments.baseline_costs(names_in(spark, sf_dir))), "query string, way string, candidates string, tuples int, infeasible boolean, rewrite_ms double")


@query()
def infeasible_by_way(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of 100 generated queries over each ontology, those that each way of finding jumps cannot rewrite."""
    return spark.createDataFrame(list(experiments.infeasible_by_way(names_in(spark, sf_dir))), "ontology string, way string, queries int, many_states int, infeasible int")


@query()
def generated_input_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of all generated queries as they are."""
    return spark.createDataFrame([r[:5] for r in experiments.generated_sizes(names_in(spark, sf_dir))], "ontology string, guided boolean, number int, states_in int, transitions_in int")


@query()
def generated_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of all generated queries before and after rewriting."""
    return spark.createDataFrame(list(experiments.generated_sizes(names_in(spark, sf_dir))), "ontology string, guided boolean, number int, states_in int, transitions_in int, states_out int, transitions_out int, tuples_minimal int")


@query()
def rewriting_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Moves and jumps of each hand-written query under each order of the passes and without each rule."""
    return spark.createDataFrame(list(experiments.rewriting_variants()), "query string, variant string, transitions_in int, transitions_out int, tuples_minimal int")


@query()
def handwritten_queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The reference's table of hand-written queries: moves, jumps, times, with a timeout of 1000 s."""
    schema = "query string, transitions_in int, transitions_out int, candidates_relevant string, tuples_minimal int, rewrite_ms double, eval_ms double, timed_out boolean, answers long, jobs int, stages int, shuffle_bytes long"
    return spark.createDataFrame(list(experiments.handwritten(spark, sf_dir)), schema)


@query()
def rewriting_correlations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How the rewriting time moves with the size of the output and with the relevant candidates, by ontology."""
    out = []
    for name, onto in experiments.ontologies(names_in(spark, sf_dir)).items():
        stats = list(workload.rewriting_stats(onto, workload.generate_queries(onto)))
        rows = spark.createDataFrame([(name, s["transitions_in"], s["transitions_out"], float(s["candidates_relevant"]), s["rewrite_ms"], s["infeasible"]) for s in stats], "ontology string, transitions_in int, transitions_out int, relevant double, ms double, infeasible boolean")
        out.append(
            rows.groupBy("ontology").agg(
                F.corr("transitions_in", "ms").alias("by_input"), F.corr("transitions_out", "ms").alias("by_output"), F.try_divide(F.covar_pop("relevant", "ms"), F.stddev_pop("relevant") * F.stddev_pop("ms")).alias("by_candidates"),
                F.percentile("ms", 0.5).alias("median_ms"), F.percentile("ms", 0.95).alias("p95_ms"), F.count_if("infeasible").alias("infeasible"),
            )
        )
    return reduce(DataFrame.unionByName, out)


EVALUATED = "ontology string, guided boolean, number int, query string, transitions_in int, transitions_out int, rewrite_ms double, eval_ms double, timed_out boolean, answers long, star boolean"


@query()
def evaluate_generated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """100 free random queries over each ontology, rewritten and evaluated over all views under a timeout of 20 s each."""
    return spark.createDataFrame(experiments.evaluated(spark, sf_dir), EVALUATED)


@query()
def evaluate_guided_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same for 100 queries over the large ontology that follow the schema of the data."""
    return spark.createDataFrame(experiments.evaluated(spark, sf_dir, experiments.GUIDED[:1]), EVALUATED)


@query()
def evaluate_guided_shop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same for 100 queries over the small ontology that follow the schema of the data."""
    return spark.createDataFrame(experiments.evaluated(spark, sf_dir, experiments.GUIDED[1:]), EVALUATED)


@query()
def evaluation_correlation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How the evaluation time moves with the moves of the output; timeouts and queries with answers. All free queries."""
    rows = spark.createDataFrame(experiments.evaluated(spark, sf_dir), EVALUATED)
    done = F.when(~F.col("timed_out"), F.col("eval_ms"))
    size = F.when(~F.col("timed_out"), F.col("transitions_out"))
    return rows.groupBy("ontology", "guided").agg(
        F.count("*").alias("queries"), F.count_if("timed_out").alias("timeouts"), F.count_if(F.col("answers") > 0).alias("with_answers"),
        F.percentile(done, 0.5).alias("median_ms"), F.max(done).alias("longest_ms"), F.try_divide(F.covar_pop(size, done), F.stddev_pop(size) * F.stddev_pop(done)).alias("time_by_output"),
    )


@query()
def concept_closure(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The closure of the large ontology's inclusions, by doubling joins."""
    return closure.saturate_concepts_df(closure.direct_inclusions(spark, workload.scaled_ontology()))


@query()
def ontology_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of the ontologies with the classes that the tables name."""
    names = names_in(spark, sf_dir)
    rows = [(name, *statistics.ontology_statistics(workload.with_names(onto, names)).values()) for name, onto in (("flat", workload.scaled_ontology()), ("shop", shop()), ("shop_18", workload.shop_18()))]
    return spark.createDataFrame(rows, "ontology string, concepts int, roles int, concept_axioms int, role_axioms int, existentials int")


def oracles() -> dict[str, str]:
    """All SQL: that over the tables, and literal rows for results that read none."""
    return ORACLES | tables.oracles()
