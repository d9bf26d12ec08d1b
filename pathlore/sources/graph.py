"""Property graphs over DataFrames.

A graph is a set of node kinds and role tables, each a DataFrame of its own with typed property columns, so a role or label
that a query doesn't name is never read and tests reach the scans. Node ids carry the kind in the top byte.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from pathlore.plans.ontology import Ontology
from pathlore.plans.terms import TOP, DataTest

KEY_BITS = 56
KINDS = {
    name: code
    for code, name in enumerate(
        "region nation customer supplier part order event turn conversation document source lang page host target brand vec class item".split(), 1
    )
}


def node_id(kind: str, key: Column) -> Column:
    return F.shiftleft(F.lit(KINDS[kind]).cast("long"), KEY_BITS) + key.cast("long")


def natural_key(id_: str | Column) -> Column:
    return F.col(id_).bitwiseAND(F.lit((1 << KEY_BITS) - 1)) if isinstance(id_, str) else id_.bitwiseAND(F.lit((1 << KEY_BITS) - 1))


def text_key(c: Column) -> Column:
    """A key of 55 bits for text."""
    return F.xxhash64(c).bitwiseAND(F.lit((1 << 55) - 1))


def test_column(t: DataTest, c: Column) -> Column:
    """A test as a filter; null, and so a missing key, fails."""
    v = F.lit(t.value)
    return {"=": c == v, "<>": c != v, "<": c < v, "<=": c <= v, ">": c > v, ">=": c >= v}[t.op]


@dataclass
class NodeKind:
    """``rows`` has node_id and the properties; a label holds for all rows (None) or where its condition does."""

    rows: DataFrame
    labels: dict[str, Column | None]
    props: tuple[str, ...] = ()


@dataclass
class PropertyGraph:
    """``roles`` have src, dst and properties. ``extra`` are labels that came by materialisation: node_id."""

    spark: SparkSession
    kinds: dict[str, NodeKind] = field(default_factory=dict)
    roles: dict[str, DataFrame] = field(default_factory=dict)
    extra: dict[str, DataFrame] = field(default_factory=dict)
    #: Which kinds all edges of a role lead from and to, where known: what cannot be is not planned.
    ends: dict[str, tuple[str, str]] = field(default_factory=dict)
    #: Whether a role leads from a node to one at most, and whether it leads into a node from one at most: used to choose plans only.
    single: dict[str, tuple[bool, bool]] = field(default_factory=dict)
    _sizes: dict[str, int] = field(default_factory=dict)

    def kind_size(self, kind: str) -> int:
        if kind not in self._sizes:
            self._sizes[kind] = self.kinds[kind].rows.count()
        return self._sizes[kind]

    # ---- what the data have (the reduced signature) ------------------------------------------------------------

    def label_names(self) -> set[str]:
        return {n for k in self.kinds.values() for n in k.labels} | set(self.extra)

    def role_names(self) -> set[str]:
        return set(self.roles)

    def role_keys(self, role: str) -> set[str]:
        return set(self.roles[role].columns) - {"src", "dst", "edge_id"}

    # ---- scans -------------------------------------------------------------------------------------------------

    def all_nodes(self) -> DataFrame:
        return reduce(DataFrame.unionByName, [k.rows.select("node_id") for k in self.kinds.values()])

    def label_nodes(self, name: str) -> DataFrame | None:
        """node_id of the nodes with a label; None if nothing can have it."""
        if name == TOP:
            return self.all_nodes()
        found = []
        for k in self.kinds.values():
            if name in k.labels:
                c = k.labels[name]
                found.append((k.rows if c is None else k.rows.where(c)).select("node_id"))
        if name in self.extra:
            found.append(self.extra[name].select("node_id"))
        return reduce(DataFrame.unionByName, found) if found else None

    def tested_nodes(self, tests: frozenset[DataTest]) -> DataFrame | None:
        keys = {t.key for t in tests}
        found = [k.rows.where(self.all_of(tests)).select("node_id") for k in self.kinds.values() if keys <= set(k.props)]
        return reduce(DataFrame.unionByName, found) if found else None

    @staticmethod
    def all_of(tests: frozenset[DataTest]) -> Column:
        return reduce(Column.__and__, [test_column(t, F.col(t.key)) for t in sorted(tests, key=str)])

    def edges(self, role: str | None, tests: frozenset[DataTest] = frozenset()) -> DataFrame | None:
        """src and dst of the edges of a role (of any role if None) that pass the tests."""
        names = [role] if role is not None else sorted(self.roles)
        keys = {t.key for t in tests}
        found = []
        for name in names:
            if name in self.roles and keys <= self.role_keys(name):
                rows = self.roles[name]
                found.append((rows.where(self.all_of(tests)) if tests else rows).select("src", "dst"))
        return reduce(DataFrame.unionByName, found) if found else None


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def commerce(g: PropertyGraph, read: Callable[[str], DataFrame]) -> None:
    region, nation, customer, supplier, part, orders, lines = (read(t) for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"))
    region_names = ("AFRICA", "AMERICA", "ASIA", "EUROPE", "MIDDLE EAST")
    g.kinds["region"] = NodeKind(region.select(node_id("region", F.col("r_regionkey")).alias("node_id"), F.col("r_name").alias("name")), {"Region": None} | {n: F.col("name") == n for n in region_names}, ("name",))
    g.kinds["nation"] = NodeKind(nation.select(node_id("nation", F.col("n_nationkey")).alias("node_id"), F.col("n_name").alias("name")), {"Nation": None}, ("name",))
    segments = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")
    g.kinds["customer"] = NodeKind(
        customer.select(node_id("customer", F.col("c_custkey")).alias("node_id"), F.col("c_acctbal").alias("acctbal"), F.col("c_name").alias("name"), F.col("c_mktsegment").alias("segment")),
        {"Customer": None} | {s: F.col("segment") == s for s in segments},
        ("acctbal", "name", "segment"),
    )
    g.kinds["supplier"] = NodeKind(supplier.select(node_id("supplier", F.col("s_suppkey")).alias("node_id"), F.col("s_acctbal").alias("acctbal"), F.col("s_name").alias("name")), {"Supplier": None}, ("acctbal", "name"))
    g.kinds["part"] = NodeKind(
        part.select(node_id("part", F.col("p_partkey")).alias("node_id"), F.col("p_size").alias("size"), F.col("p_retailprice").alias("retailprice"), F.col("p_brand").alias("brand"), F.col("p_name").alias("name"), F.col("p_type").alias("type")),
        {"Part": None} | {t: F.col("type") == t for t in ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD")},
        ("size", "retailprice", "brand", "name", "type"),
    )
    status = {"OpenOrder": "O", "FilledOrder": "F", "PendingOrder": "P"}
    g.kinds["order"] = NodeKind(
        orders.select(node_id("order", F.col("o_orderkey")).alias("node_id"), F.col("o_totalprice").alias("totalprice"), F.col("o_orderdate").alias("orderdate"), F.col("o_orderpriority").alias("priority"), F.col("o_orderstatus").alias("status")),
        {"Order": None} | {n: F.col("status") == s for n, s in status.items()},
        ("totalprice", "orderdate", "priority", "status"),
    )
    g.kinds["brand"] = NodeKind(part.select(node_id("brand", text_key(F.col("p_brand"))).alias("node_id"), F.col("p_brand").alias("name")).distinct(), {"Brand": None}, ("name",))
    edge = lambda rows, src, dst, *props: rows.select(src.alias("src"), dst.alias("dst"), *(F.col(c).alias(a) for c, a in props))
    order_of, part_of, supplier_of = node_id("order", F.col("l_orderkey")), node_id("part", F.col("l_partkey")), node_id("supplier", F.col("l_suppkey"))
    g.roles |= {
        "inRegion": edge(nation, node_id("nation", F.col("n_nationkey")), node_id("region", F.col("n_regionkey"))),
        "customerNation": edge(customer, node_id("customer", F.col("c_custkey")), node_id("nation", F.col("c_nationkey"))),
        "supplierNation": edge(supplier, node_id("supplier", F.col("s_suppkey")), node_id("nation", F.col("s_nationkey"))),
        "placed": edge(orders, node_id("customer", F.col("o_custkey")), node_id("order", F.col("o_orderkey")), ("o_orderdate", "orderdate")),
        "hasItem": edge(lines, order_of, part_of, ("l_quantity", "quantity"), ("l_extendedprice", "extendedprice"), ("l_discount", "discount"), ("l_tax", "tax"), ("l_returnflag", "returnflag"), ("l_linestatus", "linestatus"), ("l_shipdate", "shipdate")),
        "shippedBy": edge(lines, order_of, supplier_of, ("l_shipdate", "shipped")),
        "supplies": edge(lines, supplier_of, part_of).distinct(),
        "ofBrand": edge(part, node_id("part", F.col("p_partkey")), node_id("brand", text_key(F.col("p_brand")))),
    }
    g.ends |= {
        "inRegion": ("nation", "region"),
        "customerNation": ("customer", "nation"),
        "supplierNation": ("supplier", "nation"),
        "placed": ("customer", "order"),
        "hasItem": ("order", "part"),
        "shippedBy": ("order", "supplier"),
        "supplies": ("supplier", "part"),
        "ofBrand": ("part", "brand"),
    }


    g.single |= {"inRegion": (True, False), "customerNation": (True, False), "supplierNation": (True, False), "placed": (False, True), "ofBrand": (True, False)}


def activity(g: PropertyGraph, read: Callable[[str], DataFrame]) -> None:
    events, talk = read("events"), read("conversations")
    g.kinds["event"] = NodeKind(
        events.select(node_id("event", F.col("event_id")).alias("node_id"), F.col("value"), F.col("ts"), F.initcap("event_type").alias("type"), F.get_json_object("props", "$.k").cast("long").alias("k")),
        {"Event": None} | {n: F.col("type") == n for n in ("View", "Click", "Purchase", "Signup", "Error")},
        ("value", "ts", "type", "k"),
    )
    g.roles["performed"] = events.select(node_id("customer", F.col("user_id")).alias("src"), node_id("event", F.col("event_id")).alias("dst"), "ts", "value")
    later = W.partitionBy("user_id").orderBy("ts", "event_id")
    after = events.select("event_id", "ts", F.lead("event_id").over(later).alias("next_id"), F.lead("ts").over(later).alias("next_ts")).where("next_id IS NOT NULL")
    gap = F.unix_micros(F.col("next_ts").cast("timestamp")) - F.unix_micros(F.col("ts").cast("timestamp"))
    g.roles["nextEvent"] = after.select(node_id("event", F.col("event_id")).alias("src"), node_id("event", F.col("next_id")).alias("dst"), (gap / 1e6).alias("gap_s"))
    turn_id = lambda c, t: node_id("turn", F.shiftleft(F.col(c), 8) + F.col(t))
    g.kinds["turn"] = NodeKind(
        talk.select(turn_id("conv_id", "turn").alias("node_id"), "turn", F.length("text").alias("chars"), F.initcap("role").alias("speaker")),
        {"Turn": None} | {f"{r}Turn": F.col("speaker") == r for r in ("User", "Assistant", "System")},
        ("turn", "chars", "speaker"),
    )
    g.kinds["conversation"] = NodeKind(talk.select(node_id("conversation", F.col("conv_id")).alias("node_id")).distinct(), {"Conversation": None})
    g.roles["inConversation"] = talk.select(turn_id("conv_id", "turn").alias("src"), node_id("conversation", F.col("conv_id")).alias("dst"))
    order = W.partitionBy("conv_id").orderBy("turn")
    reply = talk.select("conv_id", "turn", F.lead("turn").over(order).alias("next"), F.lead(F.length("text")).over(order).alias("reply_chars")).where("next IS NOT NULL")
    g.ends |= {"performed": ("customer", "event"), "nextEvent": ("event", "event"), "inConversation": ("turn", "conversation"), "nextTurn": ("turn", "turn")}
    g.single |= {"performed": (False, True), "nextEvent": (True, True), "inConversation": (True, False), "nextTurn": (True, True)}
    g.roles["nextTurn"] = reply.select(turn_id("conv_id", "turn").alias("src"), turn_id("conv_id", "next").alias("dst"), "reply_chars")


def text(g: PropertyGraph, read: Callable[[str], DataFrame]) -> None:
    docs, labels, pages = read("documents"), read("labels"), read("pages")
    rows = docs.select("doc_id", "n_chars", "source", "lang").join(labels.select("doc_id", "quality", "toxic"), "doc_id", "left")
    g.kinds["document"] = NodeKind(rows.select(node_id("document", F.col("doc_id")).alias("node_id"), "n_chars", "quality", "toxic"), {"Document": None}, ("n_chars", "quality", "toxic"))
    for kind, column, role in (("source", "source", "fromSource"), ("lang", "lang", "inLang")):
        g.kinds[kind] = NodeKind(docs.select(node_id(kind, text_key(F.col(column))).alias("node_id"), F.col(column).alias("name")).distinct(), {kind.capitalize(): None}, ("name",))
        g.roles[role] = docs.select(node_id("document", F.col("doc_id")).alias("src"), node_id(kind, text_key(F.col(column))).alias("dst"))
    digests = docs.select("doc_id", F.unhex(F.sha2(F.col("text").cast("binary"), 256)).alias("digest"))
    groups = digests.groupBy("digest").agg(F.min("doc_id").alias("first"))
    # Copies stay factorised: each copy points at the first of its group, so a group of n copies has n - 1 edges.
    star = digests.join(groups, "digest").where("doc_id > first")
    g.roles["firstCopy"] = star.select(node_id("document", F.col("first")).alias("src"), node_id("document", F.col("doc_id")).alias("dst"))
    g.kinds["page"] = NodeKind(pages.select(node_id("page", F.col("page_id")).alias("node_id"), "url"), {"Page": None}, ("url",))
    host = F.parse_url("url", F.lit("HOST"))
    hosts = pages.select(F.col("page_id"), host.alias("host")).where("host IS NOT NULL")
    g.kinds["host"] = NodeKind(hosts.select(node_id("host", text_key(F.col("host"))).alias("node_id"), F.col("host").alias("name")).distinct(), {"Host": None}, ("name",))
    g.roles["hostedOn"] = hosts.select(node_id("page", F.col("page_id")).alias("src"), node_id("host", text_key(F.col("host"))).alias("dst"))
    links = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))
    g.kinds["target"] = NodeKind(links.select(node_id("target", text_key(F.col("href"))).alias("node_id"), F.col("href").alias("url")).distinct(), {"Target": None}, ("url",))
    g.ends |= {"fromSource": ("document", "source"), "inLang": ("document", "lang"), "firstCopy": ("document", "document"), "hostedOn": ("page", "host"), "linksTo": ("page", "target")}
    g.roles["linksTo"] = links.select(node_id("page", F.col("page_id")).alias("src"), node_id("target", text_key(F.col("href"))).alias("dst"))


def copy_pairs(g: PropertyGraph, read: Callable[[str], DataFrame]) -> None:
    """The role of all ordered pairs of exact copies. Quadratic in a group's size: only for inputs known to be small."""
    docs = read("documents").select("doc_id", F.sha2(F.col("text").cast("binary"), 256).alias("digest"))
    a, b = docs.alias("a"), docs.alias("b")
    pairs = a.join(b, (F.col("a.digest") == F.col("b.digest")) & (F.col("a.doc_id") < F.col("b.doc_id")))
    g.roles["copyOf"] = pairs.select(node_id("document", F.col("a.doc_id")).alias("src"), node_id("document", F.col("b.doc_id")).alias("dst"))


VIEWS = {"commerce": commerce, "activity": activity, "text": text, "copies": copy_pairs}


def build_graph(spark: SparkSession, sf_dir: str, views: tuple[str, ...] = ("commerce", "activity", "text")) -> PropertyGraph:
    """The graph of some views of the tables; nothing is read before a query asks."""
    g = PropertyGraph(spark)
    for v in views:
        VIEWS[v](g, lambda name: table(spark, sf_dir, name))
    return g


def signature(onto: Ontology, graph: PropertyGraph) -> dict[str, set[str]]:
    """The names that queries may use (``extended``: of ontology and data) and those that the data have (``reduced``), roles and concepts apart."""
    return {
        "extended_concepts": onto.names() | graph.label_names(), "reduced_concepts": graph.label_names(),
        "extended_roles": onto.role_names() | graph.role_names(), "reduced_roles": graph.role_names(),
    }


def graph_from_tables(nodes: DataFrame, edges: DataFrame, labels: set[str], roles: set[str]) -> PropertyGraph:
    """A graph of open tables: nodes (node_id, labels array, properties...) and edges (role, src, dst, properties...)."""
    props = tuple(c for c in nodes.columns if c not in ("node_id", "labels"))
    g = PropertyGraph(nodes.sparkSession)
    g.kinds["node"] = NodeKind(nodes, {n: F.array_contains("labels", n) for n in labels}, props)
    g.roles = {r: edges.where(F.col("role") == r).drop("role") for r in roles}
    return g


def strict_single_edge(edges: DataFrame) -> DataFrame:
    """Pairs that one role joins more than once, with the number of edges."""
    return edges.groupBy("role", "src", "dst").agg(F.count("*").alias("n_edges")).where("n_edges > 1")
