"""Standing queries on the graph of the given tables."""

from __future__ import annotations

from ..query.bgp import GraphQuery, parse_select

TEXT = {
    "W-S1": 'SELECT ?cu ?su { ?or placedBy ?cu . ?cu locatedIn ?n . ?or shippedFrom ?su . ?su locatedIn ?n . ?n locatedIn region:2 . ?or hasPriority "1-URGENT" }',
    "W-S2": 'SELECT ?b ?c { ?a followed ?b . ?a coActive ?c . ?a inSegment "BUILDING" . ?b locatedIn ?n . ?c locatedIn ?m }',
    "W-S3": 'SELECT ?n1 ?n2 { ?or placedBy ?c . ?c inSegment "BUILDING" . ?c locatedIn ?n1 . ?or hasPart ?p . ?p hasBrand "Brand#4" . ?or shippedFrom ?s . ?s locatedIn ?n2 }',
    "W-S4": "SELECT ?a ?c { ?a followed ?b . ?b followed ?c . ?a inSegment ?x . ?c inSegment ?x . ?a locatedIn ?n . ?c locatedIn ?n . ?b locatedIn ?m }",
    "W-C4": 'SELECT ?g { ?or placedBy ?c . ?c inSegment ?g . ?or hasPart ?p . ?p hasBrand "Brand#4" }',
    "W-Y4": "SELECT ?c ?n { ?or placedBy ?c . ?c locatedIn ?n . ?or shippedFrom ?s . ?s locatedIn ?n }",
    "W-K3": "SELECT ?a ?b ?c { ?a followed ?b . ?b followed ?c . ?c followed ?a }",
    "W-N": "SELECT ?l ?s { ?d writtenIn ?l . ?d fromSource ?s . ?d judged lit:good }",
    "W-P": "SELECT ?p ?q { ?p linksTo ?x . ?q linksTo ?x }",
    "W-R": "SELECT ?a ?c { ?a repliesTo ?b . ?b repliesTo ?c }",
    "W-V": "SELECT ?v ?w { ?v inCluster ?c . ?w inCluster ?c }",
    "W-M": "SELECT ?d ?e { ?d mentions ?i . ?e mentions ?i . ?d judged ?j }",
}
#: Families that a query with a variable label is evaluated on.
EVENT_LABELS = ("followed", "click", "view", "purchase", "signup")


def get(name: str) -> GraphQuery:
    if name == "W-E":
        return parse_select("SELECT ?u ?v { ?u ?act ?t . ?v ?act ?t . ?u followed ?v }", name)
    if name == "W-K3b":
        return GraphQuery(name, (), get("W-K3").body)
    if name == "W-V2":
        return GraphQuery(name, ("c",), get("W-V").body)
    return parse_select(TEXT[name], name)


def labels_of(q: GraphQuery) -> set[str]:
    return (q.labels - {"*"}) | (set(EVENT_LABELS) if "*" in q.labels else set())


def small_set() -> list[GraphQuery]:
    """Four large queries, of mean size 6.25."""
    return [get(n) for n in ("W-S1", "W-S2", "W-S3", "W-S4")]


SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")


def large_set(brands: list[str] | None = None, types: list[str] | None = None, segments=SEGMENTS, priorities=PRIORITIES) -> list[GraphQuery]:
    """215 small, overlapping queries: 77, 88, 39 and 10 of sizes 3 to 6 and one of size 7."""
    brands = brands or [f"Brand#{i}" for i in range(1, 26)]
    types = types or [f"TYPE{i}" for i in range(6)]
    nations, regions = range(25), range(5)
    at = lambda c: f"?or placedBy ?{c}"
    q3 = [f'SELECT ?c {{ {at("c")} . ?c inSegment "{s}" . ?or hasPriority "{p}" }}' for s in segments for p in priorities]
    q3 += [f'SELECT ?x {{ ?or hasPart ?p . ?p hasBrand "{b}" . ?or hasStatus ?x }}' for b in brands]
    q3 += [f"SELECT ?c {{ ?or shippedFrom ?s . ?s locatedIn nation:{n} . {at('c')} }}" for n in nations]
    q3 += [TEXT["W-K3"], "SELECT ?a ?b ?n { ?a followed ?b . ?a locatedIn ?n . ?b locatedIn ?n }"]
    q4 = [f'SELECT ?c {{ {at("c")} . ?c inSegment "{s}" . ?or hasPart ?p . ?p hasType "{t}" }}' for s in segments for t in types]
    q4 += [TEXT["W-Y4"]] + [f'SELECT ?c ?n {{ ?or hasPart ?p . ?p hasBrand "{b}" . {at("c")} . ?c locatedIn ?n }}' for b in brands]
    q4 += [f'SELECT ?n {{ ?or shippedFrom ?s . ?s locatedIn ?n . ?n locatedIn region:{r} . ?or hasPriority "{p}" }}' for r in regions for p in priorities]
    q4 += [f'SELECT ?c ?n {{ ?a followed ?b . ?b coActive ?c . ?a inSegment "{s}" . ?c locatedIn ?n }}' for s in segments]
    q4 += ["SELECT ?g ?b { ?or placedBy ?c . ?c inSegment ?g . ?or hasPart ?p . ?p hasBrand ?b }", "SELECT ?a ?b ?n { ?a coActive ?b . ?a inSegment ?x . ?b inSegment ?x . ?a locatedIn ?n }"]
    q5 = [TEXT["W-S2"].replace('"BUILDING"', f'"{s}"') for s in segments]
    five = lambda b, s: f'SELECT ?c ?n {{ ?or hasPart ?p . ?p hasBrand "{b}" . {at("c")} . ?c locatedIn ?n . ?c inSegment "{s}"'
    q5 += [five(b, s) + " }" for b in brands[:5] for s in segments]
    q5 += [TEXT["W-Y4"].replace(" }", f' . ?or hasPriority "{p}" }}') for p in priorities]
    q5 += [f'SELECT ?a ?c ?n {{ ?a followed ?b . ?b followed ?c . ?a locatedIn ?n . ?c locatedIn ?n . ?b inSegment "{s}" }}' for s in segments[:4]]
    q6 = [TEXT["W-S1"].replace("region:2", f"region:{r}") for r in regions] + [five("Brand#4", s) + " . ?or shippedFrom ?s }" for s in segments]
    return [parse_select(text, f"L{i:03d}") for i, text in enumerate([*q3, *q4, *q5, *q6, TEXT["W-S3"]])]
