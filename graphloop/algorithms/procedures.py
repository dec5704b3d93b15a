"""The analytics as procedures of the language: text that extracts a graph, loops over it and reads the result.

``LINK`` is the extraction, a statement that any other query may stand in for. Messages join
the state of a node on its own variable, so a loop moves what is sent and nothing else; state that
only grows is added to.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame

from graphloop.algorithms.reach import graph_catalog
from graphloop.plans import batches as b
from graphloop.plans.parser import parse_procedure
from graphloop.plans.procedure import Let, Loop, Procedure
from graphloop.plans.rewrite import optimise
from graphloop.plans.runtime import RunResult, run

LINK = "LET link = (SELECT DISTINCT ?node ?to WHERE { ?node g:step ?to });"
ROAD = "LET road = (SELECT ?node ?to ?cost WHERE { ?node g:step ?to BIND(1.0 AS ?cost) });"
BUSIEST = "LET start = (SELECT ?node (COUNT(*) AS ?arms) WHERE { QVALUES(link) } GROUP BY ?node ORDER BY DESC(?arms) ?node LIMIT 1);"
ENDS = """LET place = (SELECT DISTINCT ?node WHERE {
  { SELECT ?node WHERE { QVALUES(link) } } UNION { SELECT (?to AS ?node) WHERE { QVALUES(link) } }
});"""


def start_at(node: int) -> str:
    """A statement that starts a traversal at a given node."""
    return f"LET start = (SELECT ?node WHERE {{ VALUES ?node {{ {node} }} }});"


BFS = """
LET level = (SELECT ?node (0 AS ?hops) WHERE { QVALUES(start) });
LET front = (SELECT ?node ?hops WHERE { QVALUES(level) });
DO (
  LET sent = (SELECT ?to (MIN(?hops) AS ?nearest) WHERE { QVALUES(link) QVALUES(front) } GROUP BY ?to);
  LET front = (SELECT ?node ?hops WHERE {
    { SELECT (?to AS ?node) (?nearest + 1 AS ?hops) WHERE { QVALUES(sent) } } MINUS { SELECT ?node WHERE { QVALUES(level) } }
  });
  LET level = (SELECT * WHERE { { QVALUES(level) } UNION { QVALUES(front) } });
) WHILE (ASK { { SELECT (COUNT(*) AS ?found) WHERE { QVALUES(front) } } FILTER(?found = 0) });
RETURN(level);
"""

SSSP = """
LET seen = (SELECT ?node (0.0 AS ?way) WHERE { QVALUES(start) });
LET front = (SELECT ?node ?way WHERE { QVALUES(seen) });
DO (
  LET sent = (SELECT ?to (MIN(?way + ?cost) AS ?offer) WHERE { QVALUES(road) QVALUES(front) } GROUP BY ?to);
  LET front = (SELECT ?node (?offer AS ?way) WHERE {
    { SELECT (?to AS ?node) ?offer WHERE { QVALUES(sent) } }
    OPTIONAL { SELECT ?node (MIN(?way) AS ?best) WHERE { QVALUES(seen) } GROUP BY ?node }
    FILTER(COALESCE(?offer < ?best, true))
  });
  LET seen = (SELECT * WHERE { { QVALUES(seen) } UNION { QVALUES(front) } });
) WHILE (ASK { { SELECT (COUNT(*) AS ?found) WHERE { QVALUES(front) } } FILTER(?found = 0) });
LET dist = (SELECT ?node (MIN(?way) AS ?dist) WHERE { QVALUES(seen) } GROUP BY ?node);
RETURN(dist);
"""

# What a node hears pulls the node it followed along, and two hops shorten the way to the least: rounds do not grow with the diameter.
WCC = """
LET tie = (SELECT DISTINCT ?node ?to WHERE {
  { QVALUES(link) } UNION { SELECT (?to AS ?node) (?node AS ?to) WHERE { QVALUES(link) } }
});
LET part = (SELECT DISTINCT ?node (?node AS ?least) WHERE { QVALUES(tie) });
DO (
  LET sent = (SELECT ?to (MIN(?least) AS ?low) WHERE { QVALUES(tie) QVALUES(part) } GROUP BY ?to);
  LET near = (SELECT ?node ?least (IF(?low < ?least, ?low, ?least) AS ?via) WHERE {
    QVALUES(part) { SELECT (?to AS ?node) ?low WHERE { QVALUES(sent) } }
  });
  LET pull = (SELECT (?least AS ?node) (MIN(?via) AS ?deep) WHERE { QVALUES(near) } GROUP BY ?least);
  LET lead = (SELECT ?node (COALESCE(IF(?deep < ?via, ?deep, ?via), ?via) AS ?up) WHERE { QVALUES(near) OPTIONAL { QVALUES(pull) } });
  LET hop = (SELECT ?node (IF(?far < ?up, ?far, ?up) AS ?top) WHERE {
    QVALUES(lead) { SELECT (?node AS ?up) (?up AS ?far) WHERE { QVALUES(lead) } }
  });
  LET part = (SELECT ?node (IF(?far < ?top, ?far, ?top) AS ?least) WHERE {
    QVALUES(hop) { SELECT (?node AS ?top) (?top AS ?far) WHERE { QVALUES(hop) } }
  });
) WHILE (FIXPOINT(part));
RETURN(part);
"""

LCC = """
LET arc = (SELECT ?node ?to WHERE { QVALUES(link) FILTER(?node != ?to) });
LET side = (SELECT ?x ?y (COUNT(*) AS ?arcs) WHERE {
  { SELECT (IF(?node < ?to, ?node, ?to) AS ?x) (IF(?node < ?to, ?to, ?node) AS ?y) WHERE { QVALUES(arc) } }
} GROUP BY ?x ?y);
LET ring = (SELECT ?node (COUNT(*) AS ?size) WHERE {
  { SELECT (?x AS ?node) WHERE { QVALUES(side) } } UNION { SELECT (?y AS ?node) WHERE { QVALUES(side) } }
} GROUP BY ?node);
LET sized = (SELECT ?x ?y ?arcs ?p ?q WHERE {
  QVALUES(side) { SELECT (?node AS ?x) (?size AS ?p) WHERE { QVALUES(ring) } } { SELECT (?node AS ?y) (?size AS ?q) WHERE { QVALUES(ring) } }
});
LET rising = (SELECT ?a ?b ?ab WHERE {
  { SELECT (?x AS ?a) (?y AS ?b) (?arcs AS ?ab) WHERE { QVALUES(sized) FILTER(?p < ?q || (?p = ?q && ?x < ?y)) } }
  UNION { SELECT (?y AS ?a) (?x AS ?b) (?arcs AS ?ab) WHERE { QVALUES(sized) FILTER(?q < ?p || (?p = ?q && ?y < ?x)) } }
});
LET wedge = (SELECT ?a ?b ?c ?ab ?ac WHERE { QVALUES(rising) { SELECT ?a (?b AS ?c) (?ab AS ?ac) WHERE { QVALUES(rising) } } });
LET corner = (SELECT ?a ?b ?c ?ab ?ac ?bc WHERE {
  QVALUES(wedge) { SELECT (?a AS ?b) (?b AS ?c) (?ab AS ?bc) WHERE { QVALUES(rising) } }
});
LET inner = (SELECT ?node (SUM(?facing) AS ?inside) WHERE {
  { SELECT (?a AS ?node) (?bc AS ?facing) WHERE { QVALUES(corner) } }
  UNION { SELECT (?b AS ?node) (?ac AS ?facing) WHERE { QVALUES(corner) } }
  UNION { SELECT (?c AS ?node) (?ab AS ?facing) WHERE { QVALUES(corner) } }
} GROUP BY ?node);
LET clustering = (SELECT ?node (COALESCE(?inside / (?size * (?size - 1)), 0.0) AS ?lcc) WHERE {
  QVALUES(place) OPTIONAL { QVALUES(ring) } OPTIONAL { QVALUES(inner) }
});
RETURN(clustering);
"""

CDLP = """
LET hear = (SELECT ?node ?to WHERE {
  { QVALUES(link) } UNION { SELECT (?to AS ?node) (?node AS ?to) WHERE { QVALUES(link) } }
});
LET tag = (SELECT ?node (?node AS ?label) WHERE { QVALUES(place) });
DO (
  LET vote = (SELECT ?to ?label (COUNT(*) AS ?votes) WHERE { QVALUES(hear) QVALUES(tag) } GROUP BY ?to ?label);
  LET tag = (SELECT (?to AS ?node) (MIN(?label) AS ?label) WHERE {
    QVALUES(vote) { SELECT ?to (MAX(?votes) AS ?votes) WHERE { QVALUES(vote) } GROUP BY ?to }
  } GROUP BY ?to);
) WHILE (TIMES 10);
RETURN(tag);
"""

# A node passes on its damped rank in equal parts. The rest, and all that a node without links
# has, is dealt to everyone: it is known from what nodes hold, before anything is sent.
PAGERANK = """
LET fan = (SELECT ?node (0.85 / COUNT(*) AS ?part) WHERE { QVALUES(link) } GROUP BY ?node);
LET pipe = (SELECT ?node ?to ?part WHERE { QVALUES(link) QVALUES(fan) });
LET spot = (SELECT ?node (IF(BOUND(?part), 0.15, 1.0) AS ?lost) WHERE { QVALUES(place) OPTIONAL { QVALUES(fan) } });
LET size = (SELECT (COUNT(*) AS ?many) WHERE { QVALUES(spot) });
LET held = (SELECT ?node ?lost (1.0 / ?many AS ?rank) WHERE { QVALUES(spot) QVALUES(size) });
DO (
  LET sent = (SELECT ?to (SUM(?rank * ?part) AS ?gain) WHERE { QVALUES(pipe) QVALUES(held) } GROUP BY ?to);
  LET dealt = (SELECT (?pool / ?many AS ?base) WHERE { QVALUES(size) { SELECT (SUM(?rank * ?lost) AS ?pool) WHERE { QVALUES(held) } } });
  LET held = (SELECT ?node ?lost (?base + COALESCE(?gain, 0.0) AS ?rank) WHERE {
    QVALUES(spot) QVALUES(dealt) OPTIONAL { SELECT (?to AS ?node) ?gain WHERE { QVALUES(sent) } }
  });
) WHILE (TIMES 10);
RETURN(held);
"""


def pagerank_text(damping: float = 0.85) -> str:
    """PageRank over ``link`` and ``place`` with another damping."""
    return PAGERANK.replace("0.85 /", f"{damping} /").replace("0.15,", f"{round(1 - damping, 12)},")


# Orders of one brand's parts; an order cites the older ones of the same part. All of it, from the tables to the five names.
P_INDEX = """
LET dated = (SELECT DISTINCT ?part ?node ?day WHERE { ?node t:has_part ?part . ?part t:brand "Brand#7" . ?node t:order_date ?day });
LET link = (SELECT DISTINCT ?node ?to WHERE {
  QVALUES(dated) { SELECT ?part (?node AS ?to) (?day AS ?before) WHERE { QVALUES(dated) } } FILTER(?before < ?day)
});
""" + ENDS + PAGERANK.replace("RETURN(held);", """
LET winner = (SELECT ?author (SUM(?rank) AS ?p_index) WHERE { QVALUES(held) . ?node t:ordered_by ?author } GROUP BY ?author ORDER BY DESC(?p_index) ?author LIMIT 5);
LET named = (SELECT ?author ?name ?p_index WHERE { QVALUES(winner) . ?author t:customer_name ?name });
RETURN(named);
""")

# How the statement that sends is split and merged, where a procedure is evaluated in batches.
SPLITS = {
    "bfs": ("sent", ("link", "front"), b.reduce_agg(("to",), "nearest", b.F.min)),
    "sssp": ("sent", ("road", "front"), b.reduce_agg(("to",), "offer", b.F.min)),
    "wcc": ("sent", ("tie", "part"), b.reduce_agg(("to",), "low", b.F.min)),
    "cdlp": ("vote", ("hear", "tag"), b.reduce_agg(("to", "label"), "votes", b.F.sum)),
    "pr": ("sent", ("pipe", "held"), b.reduce_agg(("to",), "gain", b.F.sum)),
    "lcc": ("corner", ("wedge",), b.reduce_union()),
}
RESULTS = {
    "bfs": ("node", "CAST(hops AS BIGINT) AS level"), "sssp": ("node", "CAST(dist AS DOUBLE) AS dist"), "wcc": ("node", "least AS component"),
    "cdlp": ("node", "label"), "pr": ("node", "CAST(rank AS DOUBLE) AS rank"), "lcc": ("node", "CAST(lcc AS DOUBLE) AS lcc"),
}


def text_of(name: str, start: str = BUSIEST) -> str:
    """The whole text of an algorithm's procedure, from the extraction to the return."""
    if name == "bfs":
        return LINK + start + BFS
    if name == "sssp":
        return LINK + ROAD + start + SSSP
    if name == "wcc":
        return LINK + WCC
    return LINK + ENDS + {"lcc": LCC, "cdlp": CDLP, "pr": PAGERANK}[name]


def split_sends(proc: Procedure, name: str, how: str = "bucketed", buckets: int = 4) -> Procedure:
    """The same procedure with its sending statement evaluated in batches, by the node that sends (LCC: by the wedge's first)."""
    var, reads, reducer = SPLITS[name]
    split = b.Split("a" if name == "lcc" else "node", (), reads, reducer, how, buckets=buckets)

    def marked(statements) -> list:
        return [replace(s, body=tuple(marked(s.body))) if isinstance(s, Loop) else replace(s, split=split) if isinstance(s, Let) and s.var == var else s for s in statements]

    return Procedure(marked(proc.statements))


def solve(name: str, edges: DataFrame, source: int | None = None, mode: str = "plan", how: str = "bucketed", buckets: int = 4, timeout_s: float | None = None) -> RunResult:
    """Runs an algorithm's procedure over edges (src, dst); its columns are as ``result`` names them."""
    proc = parse_procedure(text_of(name, BUSIEST if source is None else start_at(source)))
    proc = split_sends(proc, name, how, buckets) if mode == "batched" else optimise(proc) if mode == "plan" else proc
    return run(proc, graph_catalog(edges), mode=mode, timeout_s=timeout_s)


def result(name: str, found: RunResult) -> DataFrame:
    """The answer under the names of the benchmark."""
    return found.df.selectExpr(*RESULTS[name])
