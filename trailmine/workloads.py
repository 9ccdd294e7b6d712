"""Experiment workloads on the given tables, and SQL that finds the same without an automaton."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import baselines, mining, native, post
from .operators.native import Graph, Slot
from .plans import expressions as ex
from .plans.transducers import compile_expression
from .sources import dictionary as di
from .sources import sequences as sq
from .sources.dictionary import written

SOURCES = {
    "events": (sq.event_trails, sq.event_edges),
    "sessions": (sq.event_sessions, sq.event_edges),
    "baskets": (sq.basket_trails, sq.part_edges),
    "baskets_dag": (sq.basket_trails, partial(sq.part_edges, dag=True)),
    "names": (sq.name_trails, sq.name_edges),
    "suppliers": (sq.supplier_trails, sq.supplier_edges),
    "tokens": (sq.sentence_tokens, sq.token_edges),
    "letters": (sq.letter_strings, None),
    "orders": (sq.order_trails, None),
    "roles": (sq.role_turns, None),
}
#: Sources whose items tasks read from the bytes of texts.
TEXTS = {"tokens": sq.sentence_texts, "letters": sq.letter_texts}
#: Sequences of each source at the scale for which the workloads' sigmas are stated.
SIZES = {"events": 150, "sessions": 3292, "baskets": 1500, "baskets_dag": 1500, "names": 1500, "suppliers": 1500, "tokens": 23015, "letters": 1000, "orders": 1500, "roles": 100}
_DATABASES: dict[tuple, mining.Database] = {}


def database(spark: SparkSession, sf_dir: str, source: str) -> mining.Database:
    """The prepared database of a source, kept for a session: frequencies and ids do not
    depend on the expression."""
    key = (spark.sparkContext.applicationId, sf_dir, source)
    if key not in _DATABASES:
        seqs, edges = SOURCES[source]
        found, above = seqs(spark, sf_dir), edges(spark, sf_dir) if edges else None
        _DATABASES[key] = mining.prepare_texts(TEXTS[source](spark, sf_dir), found, above) if source in TEXTS else mining.prepare(found, above)
    return _DATABASES[key]


def scaled(db: mining.Database, source: str, sigma: int) -> int:
    """``sigma`` in proportion to the number of sequences."""
    return mining.relative_sigma(sigma, SIZES[source], db.sequences)


# SQL: positions (sid, pos, item) and closures (child, anc) of the sources

_LIST = lambda xs: ", ".join(f"'{x}'" for x in xs)
_ENDS = " ".join(f"WHEN length(w) >= 4 AND w LIKE '%{e}' THEN '{k}'" for e, k in sq.ENDINGS)
_PARENT = f"""CASE WHEN w = 'be' THEN 'VERB' WHEN w IN ({_LIST(sq.BE)}) THEN 'be' WHEN w IN ({_LIST(sq.DET)}) THEN 'DET'
  WHEN w IN ({_LIST(sq.PREP)}) THEN 'PREP' WHEN w IN ({_LIST(sq.FUNC)}) THEN 'FUNC'
  WHEN length(w) >= 4 AND w LIKE '%ly' THEN 'ADV' WHEN length(w) >= 4 AND w LIKE '%ble' THEN 'ADJ'
  WHEN length(w) >= 4 AND w LIKE '%ing' THEN substr(w, 1, length(w) - 3) || '~v'
  WHEN length(w) >= 4 AND w LIKE '%ed' THEN substr(w, 1, length(w) - 2) || '~v' {_ENDS} ELSE 'NOUN' END"""

SPOTS = {
    "events": "SELECT user_id AS sid, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS pos, event_type AS item FROM events",
    "sessions": """SELECT sid, row_number() OVER (PARTITION BY sid ORDER BY ts, event_id) AS pos, item FROM (
      SELECT user_id * 1000000 + sum(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sid, ts, event_id, event_type AS item FROM (
        SELECT *, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) > 43200000000 THEN 1 ELSE 0 END AS cut FROM events))""",
    "baskets": "SELECT o_custkey AS sid, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey, l_linenumber, l_partkey) AS pos, 'P' || l_partkey AS item FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "suppliers": "SELECT o_custkey AS sid, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey, l_linenumber, l_suppkey) AS pos, 'S' || l_suppkey AS item FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "tokens": r"""SELECT doc_id * 1000000 + nth - 1 AS sid, i AS pos, lower(list_extract(ws, i)) AS item FROM (
      SELECT doc_id, nth, ws, unnest(range(1, len(ws) + 1)) AS i FROM (
        SELECT doc_id, nth, regexp_extract_all(list_extract(ss, nth), '[A-Za-z]+') AS ws FROM (
          SELECT doc_id, ss, unnest(range(1, len(ss) + 1)) AS nth FROM (
            SELECT doc_id, regexp_split_to_array(text, '[.!?\n]+') AS ss FROM documents WHERE lang = 'en'))))""",
    "letters": """SELECT doc_id AS sid, i AS pos, list_extract(ls, i) AS item FROM (
      SELECT doc_id, ls, unnest(range(1, len(ls) + 1)) AS i FROM (SELECT doc_id, regexp_extract_all(lower(text), '[a-z]') AS ls FROM documents))""",
    "orders": "SELECT o_custkey AS sid, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS pos, o_orderpriority AS item FROM orders",
    "roles": "SELECT conv_id AS sid, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS pos, role AS item FROM conversations",
}
SPOTS["baskets_dag"] = SPOTS["baskets"]
SPOTS["names"] = "SELECT o_custkey AS sid, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey, l_linenumber, l_partkey) AS pos, p_name AS item FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey"
_EVENT = "SELECT * FROM (VALUES " + ", ".join(f"('{c}', '{p}')" for c, p in sq.EVENT_EDGES) + ") AS v(child, parent)"
_NOUN = "list_extract(string_split(p_name, ' '), len(string_split(p_name, ' ')))"
_PART = f"SELECT 'P' || p_partkey AS child, p_name AS parent FROM part UNION SELECT p_name, {_NOUN} FROM part UNION SELECT {_NOUN}, 'PART' FROM part"
EDGES = {
    "events": _EVENT,
    "sessions": _EVENT,
    "baskets": _PART,
    "names": f"SELECT p_name AS child, {_NOUN} AS parent FROM part UNION SELECT {_NOUN}, 'PART' FROM part",
    "baskets_dag": _PART + " UNION SELECT 'P' || p_partkey, p_brand FROM part UNION SELECT 'P' || p_partkey, p_type FROM part",
    "suppliers": "SELECT 'S' || s_suppkey AS child, n_name AS parent FROM supplier JOIN nation ON s_nationkey = n_nationkey UNION SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey",
    "tokens": f"""SELECT w AS child, {_PARENT} AS parent FROM (SELECT DISTINCT item AS w FROM spots)
      UNION SELECT {_PARENT} AS child, 'VERB' AS parent FROM (SELECT DISTINCT item AS w FROM spots) WHERE {_PARENT} LIKE '%~v'
      UNION SELECT * FROM (VALUES ('be', 'VERB'), ('PER', 'ENTITY'), ('LOC', 'ENTITY'), ('ORG', 'ENTITY')) AS v(child, parent)""",
}
_SEEN_EVENT = f"SELECT child, parent FROM ({_EVENT}) WHERE child IN (SELECT event_type FROM events) OR child IN (SELECT parent FROM ({_EVENT}))"
_NO_EDGES = "SELECT CAST(NULL AS VARCHAR) AS child, CAST(NULL AS VARCHAR) AS parent WHERE false"


def sql_front(source: str) -> str:
    return f"""WITH RECURSIVE spots AS ({SPOTS[source]}), edges AS ({EDGES.get(source, _NO_EDGES)}),
up AS (SELECT child, parent AS anc FROM edges UNION SELECT up.child, e.parent FROM up JOIN edges e ON up.anc = e.child),
anc AS (SELECT child, anc FROM up UNION SELECT item, item FROM spots UNION SELECT child, child FROM edges UNION SELECT parent, parent FROM edges)"""


def sql_sigma(source: str, sigma: int) -> str:
    return f"(SELECT greatest(2, ({sigma} * count(DISTINCT sid) + {SIZES[source] - 1}) // {SIZES[source]}) FROM spots)"


def _sql_hits(s: Slot) -> str:
    """Places of a slot's test, once for each output that is frequent by itself."""
    where = [f"p.item = '{s.name}'" if s.exact else f"p.item IN (SELECT child FROM anc WHERE anc = '{s.name}')"] if s.name else []
    tables, out = "spots p", "p.item"
    if not s.captured:
        out = "''"
    elif s.const:
        out = f"'{s.name}'"
    elif s.up:
        tables, out = "spots p JOIN anc g ON g.child = p.item", "g.anc"
        where += [f"g.anc IN (SELECT child FROM anc WHERE anc = '{s.name}')"] if s.name else []
    if s.captured:
        where.append(f"{out} IN (SELECT item FROM often)")
    return f"SELECT DISTINCT p.sid, p.pos, replace({out}, ' ', '_') AS out FROM {tables}" + (f" WHERE {' AND '.join(where)}" if where else "")


def sql_chain(source: str, shapes: list | Graph, sigma: int) -> str:
    """Joins of positions, one step for each slot and beginning that shapes share; or one
    recursive step for a graph without gaps, whose walks may be of any length. Counted by
    sequence."""
    g = shapes if isinstance(shapes, Graph) else native.from_shapes(shapes)
    parts = [f"""{sql_front(source)}, often AS MATERIALIZED (SELECT anc.anc AS item FROM spots JOIN anc ON spots.item = anc.child GROUP BY anc.anc
      HAVING count(DISTINCT sid) >= {sql_sigma(source, sigma)})"""]
    number = {x: k for k, x in enumerate(g.slots)}
    parts += [f"h{k} AS MATERIALIZED ({_sql_hits(x)})" for x, k in number.items()]
    join = lambda s, before: f"ltrim({before} || ' ' || h.out)" if s.captured else before
    if isinstance(shapes, Graph):
        hits = " UNION ALL ".join(f"SELECT {k} AS slot, sid, pos, out FROM h{k}" for k in number.values())
        edges = ", ".join(f"({at}, {number[x]}, {to})" for at, x, _, _, to in g.edges)
        parts += [f"hits AS MATERIALIZED ({hits})", f"edges_of AS (SELECT * FROM (VALUES {edges}) AS v(node, slot, next))", f"""walk AS (
          SELECT h.sid, h.pos, e.next AS node, h.out AS pattern FROM hits h JOIN edges_of e ON e.node = 0 AND e.slot = h.slot
          UNION SELECT w.sid, h.pos, e.next, ltrim(w.pattern || ' ' || h.out) FROM walk w JOIN edges_of e ON e.node = w.node
            JOIN hits h ON h.sid = w.sid AND h.pos = w.pos + 1 AND h.slot = e.slot)"""]
        done = [f"SELECT sid, rtrim(pattern) AS pattern FROM walk WHERE node IN ({', '.join(map(str, sorted(g.ends)))})"]
    else:
        done = []
        for at, x, _, gap, to in g.edges:
            after = [e for e in g.edges if e[0] == to]
            first = bool(after) and all(e[3] is None for e in after)
            pos = "min(h.pos) AS pos" if first else "h.pos" if after else "0 AS pos"
            hits = f"h{number[x]}"
            if at and gap is None and not after:
                hits = f"(SELECT sid, out, max(pos) AS pos FROM {hits} GROUP BY sid, out)"
            if not at:
                body, pattern = f"FROM {hits} h", "h.out"
            else:
                near = "h.pos > w.pos" if gap is None else "h.pos = w.pos + 1" if gap == 0 else f"h.pos BETWEEN w.pos + 1 AND w.pos + {gap + 1}"
                body, pattern = f"FROM w{at} w JOIN {hits} h ON h.sid = w.sid AND {near}", join(x, "w.pattern")
            how = ("", " GROUP BY ALL") if first else ("DISTINCT ", "")
            parts.append(f"w{to} AS MATERIALIZED (SELECT {how[0]}h.sid AS sid, {pos}, {pattern} AS pattern {body}{how[1]})")
            if to in g.ends:
                done.append(f"SELECT sid, pattern FROM w{to}")
    return f"""{', '.join(parts)}, found AS ({' UNION '.join(done)})
SELECT pattern, CAST(len(string_split(pattern, ' ')) AS INTEGER) AS length, count(*) AS freq FROM found GROUP BY pattern
HAVING count(*) >= {sql_sigma(source, sigma)}"""


# workloads: (source, expression, sigma at sf0.01, shapes for SQL and the join plan)

ANY, UP = Slot(), Slot(up=True)


def _ctx(name: str, **k) -> Slot:
    return Slot(name, captured=False, **k)


def _be_shapes() -> list:
    out = []
    for det in (0, 1):
        for adv in (0, 1):
            for adj in (0, 1):
                slots = [Slot("ENTITY", up=True), Slot("be", up=True, const=True)] + [_ctx("DET")] * det + [Slot("ADV")] * adv + [Slot("ADJ")] * adj + [Slot("NOUN")]
                out.append((slots, [0] * (len(slots) - 1)))
    return out


def _phrase(side: Slot) -> Graph:
    """Verbs, perhaps nouns, perhaps a preposition, between entities."""
    verb, noun, prep = Slot("VERB"), Slot("NOUN"), Slot("PREP")
    moves = [(0, side, 1), (1, verb, 2), (2, verb, 2), (2, noun, 3), (3, noun, 3), (2, prep, 4), (3, prep, 4), *((k, side, 5) for k in (2, 3, 4))]
    return Graph(tuple((at, x, 0, 0 if at else None, to) for at, x, to in moves), frozenset([5]))


def _category(root: str, up: bool, gap: int, least: int, most: int) -> tuple[str, list]:
    item = f"({root}{'^' if up else ''})"
    shapes = [([Slot(root, up=up)] * k, [gap] * (k - 1)) for k in range(least, most + 1)]
    return f"{item}[.{{0,{gap}}}{item}]{{{least - 1},{most - 1}}}", shapes


def _alternatives(classes: list[list[str]], gap: int | None) -> list:
    """Shapes for slots of single letters, one shape for each choice of the first and last."""
    shapes = [[]]
    for c in classes:
        shapes = [s + [Slot(x) if x else ANY] for s in shapes for x in c]
    return [(s, [gap] * (len(s) - 1)) for s in shapes]


WORKLOADS: dict[str, tuple] = {
    "t1_events": ("events", ex.ngrams(1, 3), 60, native.skip_shapes(0, 1, 3)),
    "t1_tokens": ("tokens", ex.ngrams(1, 3), 10, native.skip_shapes(0, 1, 3)),
    "t2_events": ("events", ex.skipgrams(1, 3), 120, native.skip_shapes(1, 2, 3)),
    "t2_tokens": ("tokens", ex.skipgrams(1, 3), 50, native.skip_shapes(1, 2, 3)),
    "t2_baskets": ("baskets", ex.skipgrams(2, 2, True), 100, native.skip_shapes(2, 2, 2, True)),
    "t3_events": ("events", ex.generalized_ngrams(1, 3), 60, native.skip_shapes(0, 1, 3, True)),
    "t3_tokens": ("tokens", ex.generalized_ngrams(1, 3), 500, native.skip_shapes(0, 1, 3, True)),
    "t3_suppliers": ("suppliers", ex.generalized_ngrams(1, 2), 100, native.skip_shapes(0, 1, 2, True)),
    "p1_letters": ("letters", "([s|t]) .* (.) .* ([r|k])", 900, _alternatives([["s", "t"], [None], ["r", "k"]], None)),
    "p2_letters": ("letters", " .* ".join(f"({x})" for x in ("[i|v]", "d", "l", "g", "t", "[s|t]", ".", "[s|c]")), 500, _alternatives([["i", "v"], ["d"], ["l"], ["g"], ["t"], ["s", "t"], [None], ["s", "c"]], None)),
    "p3_letters": ("letters", "([s|t] . [r|k])", 20, _alternatives([["s", "t"], [None], ["r", "k"]], 0)),
    "p4_letters": ("letters", "([s|t] . . [d|e])", 20, _alternatives([["s", "t"], [None], [None], ["d", "e"]], 0)),
    "n1_tokens": ("tokens", "ENTITY (VERB+ NOUN+? PREP?) ENTITY", 5, _phrase(_ctx("ENTITY"))),
    "n2_tokens": ("tokens", "(ENTITY^ VERB+ NOUN+? PREP? ENTITY^)", 10, _phrase(Slot("ENTITY", up=True))),
    "n3_tokens": ("tokens", "(ENTITY^ be^=) DET? (ADV? ADJ? NOUN)", 5, _be_shapes()),
    "n4_tokens": ("tokens", "(.^){3} NOUN", 300, [([UP, UP, UP, _ctx("NOUN")], [0, 0, 0])]),
    "n5_tokens": ("tokens", "(.^ . .) | (. .^ .) | (. . .^)", 30, [([UP if k == j else ANY for k in range(3)], [0, 0]) for j in range(3)]),
    "a1_baskets": ("baskets", *(lambda e, s: (e, 60, s))(*_category("ring", True, 2, 2, 5))),
    "a2_baskets": ("names", *(lambda e, s: (e, 30, s))(*_category("ring", False, 2, 2, 5))),
    "a3_baskets": ("baskets", "'hot ring' [.{0,3} (.^)]{1,4}", 200, [([_ctx("hot ring"), *[UP] * k], [3] * k) for k in (1, 2, 3, 4)]),
    "a4_baskets": ("baskets", *(lambda e, s: (e, 60, s))(*_category("plate", True, 2, 2, 5))),
    "a1_baskets_dag": ("baskets_dag", *(lambda e, s: (e, 60, s))(*_category("ring", True, 2, 2, 5))),
    "log_after_error": ("events", "error (.)", 100, [([_ctx("error"), ANY], [0])]),
    "log_before_error": ("events", "(.) error", 100, [([ANY, _ctx("error")], [0])]),
    "log_between_errors": ("events", "error ([ACTION^]{1,4}) error", 100, [([_ctx("error"), *[Slot("ACTION", up=True)] * k, _ctx("error")], [0] * (k + 1)) for k in range(1, 5)]),
    "adj_noun": ("tokens", "(ADJ NOUN) | (ADJ^= NOUN)", 5, [([Slot("ADJ"), Slot("NOUN")], [0]), ([Slot("ADJ", up=True, const=True), Slot("NOUN")], [0])]),
    "c1_all_subsequences": ("roles", ex.all_subsequences(), 20, native.skip_shapes(None, 1, 8)),
    "c2_bounded_length": ("sessions", ex.bounded_length(1, 3), 100, native.skip_shapes(None, 1, 3)),
    "c3_ngrams": ("sessions", ex.ngrams(2, 3), 60, native.skip_shapes(0, 2, 3)),
    "c4_bounded_gap": ("sessions", ex.bounded_gap(1, 2, 3), 80, native.skip_shapes(1, 2, 3)),
    "c5_serial_episode": ("sessions", ex.serial_episode(3, 2), 60, [([ANY] * 3, [a, b]) for a, b in ((0, 2), (1, 1), (2, 0))]),
    "c6_generalized": ("sessions", ex.generalized_ngrams(1, 2), 100, native.skip_shapes(0, 1, 2, True)),
    "c7_regex_subsequences": ("sessions", ex.regex_subsequences(["error", ".", "[view|click]"]), 20, [([Slot("error"), ANY, Slot(x)], [None, None]) for x in ("view", "click")]),
    "c8_regex_contiguous": ("sessions", ex.regex_contiguous("[view|click] purchase"), 20, [([Slot(x), Slot("purchase")], [0]) for x in ("view", "click")]),
    "c9_bounded_span": ("sessions", ex.bounded_span(3, 2, 3), 100, [([ANY, ANY], [1]), ([ANY] * 3, [0, 0])]),
    "c10_context": ("sessions", ex.between("view", ".^", "error"), 20, [([_ctx("view"), UP, _ctx("error")], [0, 0])]),
    "c11_generalized_skipgrams": ("sessions", ex.skipgrams(1, 2, True), 100, native.skip_shapes(1, 2, 2, True)),
    "order_priorities": ("orders", ex.ngrams(1, 2), 100, native.skip_shapes(0, 1, 2)),
}
GOLDEN = "[c|d]([A^|B^=]+)e"
#: Workloads over which the methods are compared.
COMPARED = ("n1_tokens", "n2_tokens", "n3_tokens", "n4_tokens", "n5_tokens", "a1_baskets", "a2_baskets", "a3_baskets", "a4_baskets")


def run(name: str, method: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    source, expression, sigma, _ = WORKLOADS[name]
    db = database(spark, sf_dir, source)
    return mining.mine(db, expression, scaled(db, source, sigma), method=method)


def run_joins(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    source, _, sigma, shapes = WORKLOADS[name]
    db = database(spark, sf_dir, source)
    return di.decode(native.chain(db, shapes, scaled(db, source, sigma)), db.dictionary)


def golden(spark: SparkSession, sf_dir: str) -> DataFrame:
    seqs = [["c", "a1", "b12", "e"], ["a1", "b2", "e"], ["d", "a2", "a1", "a2", "b11", "e"], ["d", "a1", "B", "e"], ["e", "a1", "b2", "d"], ["c", "a1", "a1", "a1", "b2", "e"]]
    edges = [("a1", "A"), ("a2", "A"), ("b1", "B"), ("b2", "B"), ("b11", "b1"), ("b12", "b1")]
    db = mining.prepare(spark.createDataFrame(list(enumerate(seqs, 1)), "sid long, items array<string>"), spark.createDataFrame(edges, "child string, parent string"))
    return mining.mine(db, GOLDEN, 2, "full", "growth")


def _baseline(kind: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    source, sigma = ("letters", 20) if kind.startswith("regex") else ("suppliers", 100) if kind.endswith("up") else ("events", 120)
    db = database(spark, sf_dir, source)
    sigma, common = scaled(db, source, sigma), scaled(db, source, 149)
    found = {
        "vertical": lambda: baselines.vertical_mine(db, sigma, 3, 1),
        "vertical_up": lambda: baselines.vertical_mine(db, sigma, 2, 0, True, 1),
        "prefix_growth": lambda: baselines.prefix_growth_mine(db, sigma, 3, 1, min_len=2),
        "prefix_growth_up": lambda: baselines.prefix_growth_mine(db, sigma, 2, 0, True, 1),
        "prefix_span": lambda: baselines.prefix_span(db, common, 3),
        "prefix_span_mllib": lambda: baselines.prefix_span_mllib(db, common, 3),
        "regex_growth": lambda: baselines.prefix_growth_regex(db, "[s|t] . [r|k]", sigma, True),
        "regex_enumerate": lambda: baselines.regex_enumerate(db, "[s|t] . [r|k]", sigma, True),
    }[kind]()
    return di.decode(found, db.dictionary)


BASELINES = {
    "vertical": "t2_events", "vertical_up": "t3_suppliers", "prefix_growth": "t2_events", "prefix_growth_up": "t3_suppliers",
    "regex_growth": "p3_letters", "regex_enumerate": "p3_letters",
}


def _flist(source: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return database(spark, sf_dir, source).dictionary.items.where("freq > 0").select("item", "freq")


def _flist_sql(source: str) -> str:
    return f"{sql_front(source)} SELECT anc AS item, count(DISTINCT sid) AS freq FROM spots JOIN anc ON spots.item = anc.child GROUP BY anc"


def _lengths(source: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return SOURCES[source][0](spark, sf_dir).groupBy(F.size("items").cast("long").alias("length")).agg(F.count(F.lit(1)).alias("n")).where("length > 0")


def _lengths_sql(source: str) -> str:
    return f"WITH spots AS ({SPOTS[source]}) SELECT length, count(*) AS n FROM (SELECT count(*) AS length FROM spots GROUP BY sid) GROUP BY length"


def _closure(source: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return di.closure((sq.seen_event_edges if source == "events" else SOURCES[source][1])(spark, sf_dir))


def _mean(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    source, expression, sigma, _ = WORKLOADS[name]
    db = database(spark, sf_dir, source)
    r = mining.mean_outputs(db, compile_expression(expression, "anywhere"), scaled(db, source, sigma))
    return r.select("n_sequences", "n_pairs")


def _plain_moves(t, d: di.Dictionary) -> int:
    """Moves of the plain form, by counts of the pairs on which labels match."""
    ids = {r["item"]: r["fid"] for r in d.items.where(F.col("item").isin(sorted(t.names))).collect()}
    if lost := t.names - set(ids):
        raise ValueError(f"the expression names items that are not in the dictionary: {', '.join(sorted(lost))}")

    def size(i: tuple, o: tuple | None) -> int:
        below = d.pairs.where(F.col("anc") == ids[i[1]]) if i[0] == "below" else d.items.where(F.col("item") == i[1]) if i[0] == "is" else d.items
        below = below.select("fid")
        if not o or o[0] in ("self", "const"):
            return below.count()
        pairs = d.pairs.join(below, "fid", "left_semi")
        if o[0] == "upto":
            pairs = pairs.join(d.pairs.where(F.col("anc") == ids[o[1]]).select(F.col("fid").alias("anc")), "anc", "left_semi")
        return pairs.count()

    sizes = {x: size(*x) for x in {(i, o) for ms in t.moves for i, o, _ in ms}}
    return sum(sizes[i, o] for ms in t.moves for i, o, _ in ms)


def transducer_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """States and transitions of each compared workload: as built, reduced, and plain over the
    items of its hierarchy (by formula on label matches, counted by Spark)."""
    rows = []
    for name in COMPARED:
        source, expression, _, _ = WORKLOADS[name]
        raw, small = compile_expression(expression, "anywhere", False), compile_expression(expression, "anywhere")
        rows.append((name, *raw.size, *small.size, _plain_moves(small, database(spark, sf_dir, source).dictionary)))
    return spark.createDataFrame(rows, "workload string, built_states int, built_moves int, states int, moves int, plain_moves long")


def mining_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Search effort by level of growth on the compared workloads over baskets."""
    rows = []
    for name in ("a1_baskets", "a3_baskets"):
        source, expression, sigma, _ = WORKLOADS[name]
        report = mining.Report()
        db = database(spark, sf_dir, source)
        mining.snapshot_growth(db, compile_expression(expression, "anywhere"), scaled(db, source, sigma), report=report)
        rows += [(name, x["level"], x["created"], x["survived"], x["snapshots"], x["bytes"]) for x in report.levels]
    return spark.createDataFrame(rows, "workload string, level int, created long, survived long, snapshots long, bytes long")


def method_equality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``workload, method, n_rows, n_differing``: patterns of each method, and rows in which it
    differs from the joins."""
    out = None
    for name in ("a1_baskets", "a2_baskets"):
        base = written(run(name, "joins", spark, sf_dir), "joins")
        for method in ("naive", "pruned", "growth", "plain"):
            other = written(run(name, method, spark, sf_dir), method)
            rows = other.agg(F.count(F.lit(1)).alias("n_rows")).join(post.disagreement(base, other).agg(F.count(F.lit(1)).alias("n_differing")))
            rows = rows.select(F.lit(name).alias("workload"), F.lit(method).alias("method"), "n_rows", "n_differing")
            out = rows if out is None else out.unionByName(rows)
    return out


def dataset_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sequences, lengths and distinct items of each source."""
    out = None
    for source in SPOTS:
        rows = di.sequence_stats(SOURCES[source][0](spark, sf_dir).where(F.size("items") > 0)).select(F.lit(source).alias("source"), "*")
        out = rows if out is None else out.unionByName(rows)
    return out.select("source", "n_sequences", F.round("avg_length", 6).alias("avg_length"), F.col("max_length").cast("long").alias("max_length"), "total_items", "distinct_items")


def _dataset_sql(source: str) -> str:
    return f"""SELECT '{source}' AS source, count(*) AS n_sequences, round(avg(n), 6) AS avg_length, max(n) AS max_length, CAST(sum(n) AS BIGINT) AS total_items,
      (SELECT count(DISTINCT item) FROM ({SPOTS[source]})) AS distinct_items FROM (SELECT sid, count(*) AS n FROM ({SPOTS[source]}) GROUP BY sid)"""


def queries() -> dict:
    out = {name: partial(run, name, "auto") for name in WORKLOADS}
    out |= {f"{name}_growth": partial(run, name, "growth") for name in (*COMPARED, "t1_events", "t2_events", "t3_events")}
    out |= {f"{name}_pruned": partial(run, name, "pruned") for name in COMPARED}
    out |= {f"{name}_naive": partial(run, name, "naive") for name in ("n1_tokens", "n2_tokens", "n3_tokens", "a1_baskets", "a2_baskets", "a4_baskets", "t2_events")}
    out |= {f"{name}_plain": partial(run, name, "plain") for name in ("a1_baskets", "a2_baskets", "a4_baskets")}
    out |= {f"{name}_joins": partial(run_joins, name) for name in ("a2_baskets", "n2_tokens", "t2_events", "t3_suppliers", "n3_tokens", "n4_tokens", "n5_tokens", "a1_baskets", "a3_baskets", "p3_letters", "log_after_error")}
    out |= {f"base_{k}": partial(_baseline, k) for k in (*BASELINES, "prefix_span", "prefix_span_mllib")}
    out |= {f"flist_{s}": partial(_flist, s) for s in ("events", "baskets", "baskets_dag", "suppliers", "tokens")}
    out |= {f"lengths_{s}": partial(_lengths, s) for s in SPOTS if s not in ("baskets_dag", "names")}
    out |= {f"hierarchy_closure_{s}": partial(_closure, s) for s in ("events", "baskets_dag", "suppliers", "tokens")}
    out |= {"mean_outputs_a3": partial(_mean, "a3_baskets"), "golden": golden, "transducer_sizes": transducer_sizes, "mining_report": mining_report, "method_equality": method_equality, "dataset_stats": dataset_stats}
    out["topk_patterns"] = lambda s, d: post.top_k(run("t1_tokens", "auto", s, d), 20)
    out["rollup_lengths"] = lambda s, d: post.by_length(run("t1_tokens", "auto", s, d))
    out["maximal_patterns"] = lambda s, d: post.maximal(run("a3_baskets", "auto", s, d))
    out["closed_patterns"] = lambda s, d: post.closed(run("a3_baskets", "auto", s, d))
    return out


def oracle_sql() -> dict[str, str]:
    base = {name: sql_chain(source, shapes, sigma) for name, (source, _, sigma, shapes) in WORKLOADS.items() if shapes}
    out = dict(base)
    for name in queries():
        stem = name.rpartition("_")[0]
        if name not in out and stem in base and name.rpartition("_")[2] in ("growth", "pruned", "naive", "plain", "joins"):
            out[name] = base[stem]
    out |= {f"base_{k}": base[w] for k, w in BASELINES.items()}
    span = sql_chain("events", native.skip_shapes(None, 1, 3), 149)
    out |= {"base_prefix_span": span, "base_prefix_span_mllib": span}
    out |= {f"flist_{s}": _flist_sql(s) for s in ("events", "baskets", "baskets_dag", "suppliers", "tokens")}
    out |= {f"lengths_{s}": _lengths_sql(s) for s in SPOTS if s not in ("baskets_dag", "names")}
    out |= {f"hierarchy_closure_{s}": f"{sql_front(s)} SELECT child, anc FROM up" for s in ("events", "baskets_dag", "suppliers", "tokens")}
    out["hierarchy_closure_events"] = f"""WITH RECURSIVE edges AS ({_SEEN_EVENT}),
up AS (SELECT child, parent AS anc FROM edges UNION SELECT up.child, e.parent FROM up JOIN edges e ON up.anc = e.child) SELECT child, anc FROM up"""
    out["golden"] = "SELECT pattern, CAST(length AS INTEGER) AS length, CAST(freq AS BIGINT) AS freq FROM (VALUES ('A A A B', 4, 2), ('A B', 2, 2), ('A a1 A B', 4, 2), ('a1 B', 2, 2)) AS v(pattern, length, freq)"
    a3 = base["a3_baskets"]
    longer = f"""WITH RECURSIVE r AS MATERIALIZED ({a3}), x AS (SELECT pattern, length, freq, string_split(pattern, ' ') AS w FROM r),
held AS (
  SELECT p.pattern, q.pattern AS q, 1 AS k, list_position(q.w, p.w[1]) AS place FROM x p JOIN x q ON q.length > p.length AND list_contains(q.w, p.w[1])
  UNION ALL SELECT h.pattern, h.q, k + 1, place + list_position(q.w[place + 1:], p.w[k + 1]) FROM held h JOIN x p ON p.pattern = h.pattern JOIN x q ON q.pattern = h.q
  WHERE k < p.length AND list_contains(q.w[place + 1:], p.w[k + 1]))
SELECT pattern, length, freq FROM x WHERE NOT EXISTS (SELECT 1 FROM held h JOIN x q ON q.pattern = h.q WHERE h.pattern = x.pattern AND h.k = x.length"""
    out["maximal_patterns"] = longer + ")"
    out["closed_patterns"] = longer + " AND q.freq = x.freq)"
    out["dataset_stats"] = " UNION ALL ".join(_dataset_sql(x) for x in SPOTS)
    out["method_equality"] = " UNION ALL ".join(
        f"SELECT '{name}' AS workload, m.method, (SELECT count(*) FROM ({base[name]})) AS n_rows, CAST(0 AS BIGINT) AS n_differing FROM (VALUES ('naive'), ('pruned'), ('growth'), ('plain')) AS m(method)"
        for name in ("a1_baskets", "a2_baskets"))
    out["topk_patterns"] = f"SELECT * FROM ({base['t1_tokens']}) ORDER BY freq DESC, pattern LIMIT 20"
    out["rollup_lengths"] = f"SELECT length, count(*) AS n_patterns, max(freq) AS max_freq FROM ({base['t1_tokens']}) GROUP BY length"
    return out
