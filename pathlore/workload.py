"""The experiment workloads: hand-written queries, scaled ontologies and generated queries."""

from __future__ import annotations

import random
from collections.abc import Iterator
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathlore.plans.ontology import SHOP, ConceptAxiom, Name, Ontology, RoleAxiom, parse_ontology
from pathlore.plans.terms import Role

#: Queries that mirror the worked examples (w) and the hand-written ones over an ontology with existentials (v).
QUERIES = {
    "w1_cobuyer_star": "ans(x,y) <- [acctbal>=9900]/(placed/{hasItem,quantity>=49}/itemOf/^placed)*/placed(x,y) & <deal>/:Tracked(y,z)",
    "w2_part_to_error_customer": "ans(x,y) <- {itemOf,quantity>=50}/^placed/[acctbal>=5000](x,y) & :Error/^performed(z,y)",
    "w3_reply_chain": "ans(x,y) <- [turn=0]/({nextTurn,reply_chars>=50}/<inConversation>)*(x,y)",
    "w4_local_supplier": "ans(x,y) <- :Buyer/placed/shippedBy/:Organisation(x,y) & locatedIn/:Nation/^customerNation(y,x)",
    "v1_licensed": "ans(x) <- :Party/[acctbal>=5000]/holdsLicence/issuedBy/:Authority(x,w)",
    "v2_accredited_region": "ans(x,y) <- :Organisation/accreditedBy/licenceOf/locatedIn/inRegion(x,y)",
    "v3_handled_supplier": "ans(x) <- placed/handledBy/:Agent(x,w)",
    "v4_tracked_brand": "ans(x,y) <- :Tracked/hasItem/<^bulkDeal/assignedTo>/ofBrand(x,y)",
    "v5_licence_star": "ans(x,y) <- (accreditedBy/licenceOf)*/^shippedBy/:BulkOrder(x,y)",
}
#: Which views of the tables each needs.
VIEWS = {"w2_part_to_error_customer": ("commerce", "activity"), "w3_reply_chain": ("activity",)}

DATA_ROLES = ("customerNation", "supplierNation", "inRegion", "placed", "hasItem", "shippedBy", "ofBrand")
SHOP_ROLES = (*DATA_ROLES, "locatedIn", "involvedIn", "itemOf", "bulkDeal", "deal", "holdsLicence", "accreditedBy", "licenceOf", "handledBy", "assignedTo", "issuedBy")


def shop_18() -> Ontology:
    """53 concepts and 18 roles, with existentials."""
    keep = []
    for line in SHOP.splitlines():
        words = line.replace(",", " ").replace("^", " ").replace("<", " ").split()
        if words[:1] == ["role"] and "{" not in line and not set(words[1:]) <= set(SHOP_ROLES):
            continue
        if words:
            keep.append(line)
    onto = parse_ontology("\n".join(keep))
    pads = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"], ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"], ["OpenOrder", "FilledOrder", "PendingOrder"], ["AFRICA", "AMERICA", "ASIA", "EUROPE"]
    for group, above in zip(pads, ("Customer", "Part", "Order", "Region"), strict=True):
        for n in group:
            if len(onto.names() | {n, above}) <= 53:
                onto.concepts.append(ConceptAxiom(Name(n), Name(above)))
    extra = 0
    while len(onto.names()) < 53:
        onto.concepts.append(ConceptAxiom(Name(f"SpecialPart{extra}"), Name("Part")))
        extra += 1
    return Ontology(onto.concepts, onto.roles)


def scaled_ontology(n_concepts: int = 1230, n_roles: int = 1212, seed: int = 42) -> Ontology:
    """No existentials on the right and very many names: trees of concepts above Part, Party and Order, chains above data roles."""
    rng = random.Random(seed)
    roots = ["Part", "Party", "Order"]
    concepts = [ConceptAxiom(Name("Customer"), Name("Party")), ConceptAxiom(Name("Supplier"), Name("Party"))]
    names = [*roots, "Customer", "Supplier"]
    i = 0
    while len(names) < n_concepts:
        n = f"{rng.choice(['Brand', 'Type', 'Band', 'Area'])}Group{i}"
        concepts.append(ConceptAxiom(Name(rng.choice(names)), Name(n)) if rng.random() < 0.3 else ConceptAxiom(Name(n), Name(rng.choice(names))))
        names.append(n)
        i += 1
    roles, all_roles = [], list(DATA_ROLES)
    i = 0
    while len(all_roles) < n_roles:
        n = f"relation{i}"
        roles.append(RoleAxiom(Role(rng.choice(all_roles), rng.random() < 0.1), Role(n)))
        all_roles.append(n)
        i += 1
    return Ontology(concepts, roles)


#: Columns whose values are names of classes: table, column, what a name begins with, the concept above.
VALUE_NAMES = [
    ("customer", "c_mktsegment", "", "Customer"), ("part", "p_type", "", "Part"), ("part", "p_brand", "", "Part"), ("region", "r_name", "", "Region"),
    ("orders", "o_orderstatus", "Status_", "Order"), ("orders", "o_orderpriority", "Priority_", "Order"), ("events", "event_type", "Event_", "Event"),
]


def table_names(spark: SparkSession, sf_dir: str) -> list[tuple[str, str]]:
    """Each class that the tables' values name, and the concept above it, in order. Nulls name none; signs become underscores."""
    from pathlore.sources.graph import table

    rows = [table(spark, sf_dir, t).where(F.col(c).isNotNull()).select(F.concat(F.lit(p), F.regexp_replace(F.col(c), r"[^0-9A-Za-z]+", "_")).alias("name"), F.lit(above).alias("above")).distinct() for t, c, p, above in VALUE_NAMES]
    return [tuple(r) for r in reduce(DataFrame.unionByName, rows).orderBy("name", "above").collect()]


def with_names(onto: Ontology, names: list[tuple[str, str]]) -> Ontology:
    """The ontology with the classes that the tables name, each below its concept; inclusions that it has are not repeated."""
    known = {(str(a.left), str(a.right)) for a in onto.concepts}
    return Ontology([*onto.concepts, *(ConceptAxiom(Name(n), Name(above)) for n, above in names if (n, above) not in known)], list(onto.roles))


#: What each data role leads from and to, for queries that follow the schema.
SCHEMA = {"customerNation": ("Customer", "Nation"), "supplierNation": ("Supplier", "Nation"), "inRegion": ("Nation", "Region"), "placed": ("Customer", "Order"), "hasItem": ("Order", "Part"), "shippedBy": ("Order", "Supplier"), "ofBrand": ("Part", "Brand")}


def generate_queries(onto: Ontology, n: int = 100, seed: int = 42, min_len: int | None = None, max_len: int | None = None, max_nest: int = 2, p_union: float = 0.2, p_star: float = 0.2, guided: bool = False) -> list[str]:
    """Random nested path queries of bounded length and nesting: concatenation, union, star, nested tests, label tests.

    Free ones take any name of the ontology and by default have 8 to 20 pieces, so that about 60 of 100 have 30 states or more.
    Guided ones follow the schema of the data, so that they can have answers; by default they have 4 pieces at most.
    """
    rng = random.Random(seed)
    names, roles = sorted(onto.names()), sorted(onto.role_names())
    min_len, max_len = min_len or (1 if guided else 8), max_len or (4 if guided else 20)

    def free(least: int, most: int, nest: int) -> str:
        return "/".join(piece(nest) for _ in range(rng.randint(least, most)))

    def piece(nest: int) -> str:
        x = rng.random()
        if x < p_union:
            return f"({one(nest)}|{one(nest)})"
        if x < p_union + p_star:
            return f"({one(nest)})*"
        return one(nest)

    def one(nest: int) -> str:
        x = rng.random()
        if nest and x < 0.2:
            return f"<{free(1, 3, nest - 1)}>"
        if x < 0.4:
            return ":" + rng.choice(names)
        return "^" * (rng.random() < 0.3) + rng.choice(roles)

    def walk(length: int, nest: int, at: str, end: bool = True) -> str:
        out: list[str] = []
        for _ in range(rng.randint(1, length)):
            ways = [(r, False, b) for r, (a, b) in SCHEMA.items() if a == at] + [(r, True, a) for r, (a, b) in SCHEMA.items() if b == at and at not in ("Nation", "Region", "Brand")]
            if not ways:
                break
            r, inverse, to = rng.choice(ways)
            supers = sorted(x.name for x in onto.role_supers(Role(r)) if not x.inverse)
            step = "^" * inverse + rng.choice(supers)
            same = [w for w in ways if w[2] == to and w[0] != r]
            if same and rng.random() < p_union:
                step = f"({step}|{'^' * same[0][1]}{same[0][0]})"
            if nest and rng.random() < 0.2:
                out.append(f"<{walk(2, nest - 1, at)}>")
            #: A star needs equal ends: the step and a way back, by the same role or by another that leads there.
            if rng.random() < p_star:
                back = rng.choice([("^" * (not inverse)) + r, *("^" * (not v) + w for w, v, t in ways if t == to and w != r)])
                out.append(f"({step}/{back})*")
                continue
            out.append(step)
            at = to
        return "/".join(out)

    out = []
    for _ in range(n):
        if guided:
            first = rng.choice(["Customer", "Order", "Part", "Supplier"])
            out.append(f"ans(x,y) <- :{first}/{walk(max_len, max_nest, first)}(x,y)")
        else:
            out.append(f"ans(x,y) <- {free(min_len, max_len, max_nest)}(x,y)")
    return out


def rewriting_stats(onto: Ontology, queries: list[str]) -> Iterator[dict]:
    """The cost measures of each rewriting."""
    from pathlore.plans.query import parse_query
    from pathlore.plans.rewrite import rewrite

    for text in queries:
        s = rewrite(parse_query(text), onto).stats
        yield {"query": text, **{k: getattr(s, k) for k in ("states_in", "states_out", "transitions_in", "transitions_out", "tuples_minimal", "infeasible", "rewrite_ms")}, "candidates_all": str(s.candidates_all), "candidates_relevant": str(s.candidates_relevant)}
