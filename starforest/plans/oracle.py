"""Oracle SQL (DuckDB dialect): edge tables, and forests by rounds of contraction written out as common table expressions."""

from __future__ import annotations


def vid(key: str, kind: int) -> str:
    return f"(CAST({key} AS BIGINT) * 16 + {kind})"


CENTS = "CAST(round(l_extendedprice * 100) AS BIGINT)"


def _edges(a: str, b: str, w: str, source: str, agg: str = "min") -> str:
    return f"SELECT least(a, b) AS lo, greatest(a, b) AS hi, CAST({agg}(w) AS BIGINT) AS w FROM (SELECT {a} AS a, {b} AS b, {w} AS w FROM {source}) WHERE a <> b GROUP BY 1, 2"


_US = "(epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01 00:00:00'))"
_NEXT = "SELECT a, lead(a) OVER w AS b, lead(us) OVER w - us AS w FROM (SELECT " + vid("event_id", 6) + f" AS a, user_id, {_US} AS us FROM events) WINDOW w AS ({{}}ORDER BY us, a)"
_SEQ = "SELECT least(a, b) AS lo, greatest(a, b) AS hi, min(w) AS w FROM ({}) WHERE b IS NOT NULL AND a <> b GROUP BY 1, 2"

EDGES = {
    "trade": _edges(vid("o_custkey", 0), vid("l_suppkey", 1), CENTS, "lineitem JOIN orders ON l_orderkey = o_orderkey"),
    "supply": _edges(vid("l_partkey", 2), vid("l_suppkey", 1), CENTS, "lineitem"),
    "basket": "SELECT x.item AS lo, y.item AS hi, min(x.c + y.c) AS w FROM (SELECT l_orderkey, {i} AS item, {c} AS c FROM lineitem) x JOIN (SELECT l_orderkey, {i} AS item, {c} AS c FROM lineitem) y ON x.l_orderkey = y.l_orderkey AND x.item < y.item GROUP BY 1, 2".format(i=vid("l_partkey", 2), c=CENTS),
    "returns": _edges(vid("l_orderkey", 3), vid("l_partkey", 2), CENTS, "lineitem WHERE l_returnflag = 'R' AND l_quantity >= 45"),
    "nation": _edges(vid("c_nationkey", 4), vid("s_nationkey", 4), CENTS, "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey", "sum"),
    "sessions": _SEQ.format(_NEXT.format("PARTITION BY user_id ")),
    "lattice": _SEQ.format(_NEXT.format("") + " UNION ALL " + _NEXT.format("PARTITION BY user_id ")),
    "turns": "SELECT least(a, b) AS lo, greatest(a, b) AS hi, min(w) AS w FROM (SELECT {v} AS a, lead({v}) OVER (PARTITION BY conv_id ORDER BY turn) AS b, length(text) AS w FROM conversations) WHERE b IS NOT NULL GROUP BY 1, 2".format(v=vid("conv_id * 1000 + turn", 12)),
    "nearcopy": "WITH t AS (SELECT DISTINCT {v} AS v, unnest(string_split(text, chr(10))) AS t FROM documents), s AS (SELECT * FROM t WHERE length(t) >= 20) SELECT x.v AS lo, y.v AS hi, 1000 - count(*) AS w FROM s x JOIN s y ON x.t = y.t AND x.v < y.v GROUP BY 1, 2".format(v=vid("doc_id", 7)),
    "links": "SELECT least(a, b) AS lo, greatest(a, b) AS hi, min(w) AS w FROM (SELECT a, CAST(('0x' || substr(md5(href), 1, 13)) AS BIGINT) * 16 + 10 AS b, CAST(i - 1 AS BIGINT) AS w FROM (SELECT a, h[i] AS href, i FROM (SELECT {v} AS a, regexp_extract_all(html, 'href=\"([^\"]*)\"', 1) AS h FROM pages), range(1, 10000) r(i) WHERE i <= len(h))) GROUP BY 1, 2".format(v=vid("page_id", 9)),
    "geo": "SELECT least(a, b) AS lo, greatest(a, b) AS hi, CAST(min(w) AS BIGINT) AS w FROM (SELECT {n} AS a, {r} AS b, n_nationkey AS w FROM nation UNION ALL SELECT {c}, {cn}, c_custkey FROM customer UNION ALL SELECT {s}, {sn}, s_suppkey FROM supplier) GROUP BY 1, 2".format(n=vid("n_nationkey", 4), r=vid("n_regionkey", 5), c=vid("c_custkey", 0), cn=vid("c_nationkey", 4), s=vid("s_suppkey", 1), sn=vid("s_nationkey", 4)),
}

_APART = "sqrt(list_sum(list_transform(range(1, 65), lambda k: (CAST(x.embedding[k] AS DOUBLE) - y.embedding[k]) * (CAST(x.embedding[k] AS DOUBLE) - y.embedding[k]))))"
VECTOR_EDGES = f"SELECT lo, hi, CAST(round(d * 1000) AS BIGINT) AS w FROM (SELECT {vid('x.vec_id', 8)} AS lo, {vid('y.vec_id', 8)} AS hi, {_APART} AS d FROM embeddings x JOIN embeddings y ON x.vec_id < y.vec_id) WHERE d <= 1.15"

RANKED = "e AS MATERIALIZED (SELECT row_number() OVER (ORDER BY w, lo, hi) - 1 AS rank, lo, hi, w FROM ({}))"


def mixed_sql(*parts: str) -> str:
    """The integer mixer of :func:`starforest.graph.order.mixed`."""
    h = "CAST(17 AS BIGINT)"
    for p in parts:
        one = f"(({h} * 69069 + CAST({p} AS BIGINT) % 2147483647 + 1) % 2147483647)"
        h = f"(({one} * {one} + 48271) % 2147483647)"
    return f"(({h} * 16807 + {h} // 8191) % 2147483647)"


def forest_ctes(edges: str, rounds: int = 9, doublings: int = 5) -> str:
    """Common table expressions that end in ``f(rank, round)``: every round picks each tree's lightest outgoing edge and contracts."""
    out = [RANKED.format(edges), "p0 AS MATERIALIZED (SELECT v, v AS p FROM (SELECT lo AS v FROM e UNION SELECT hi FROM e))"]
    for k in range(rounds):
        out += [
            f"a{k} AS MATERIALIZED (SELECT rank, hi, p AS pl FROM e JOIN p{k} ON lo = v)",
            f"b{k} AS MATERIALIZED (SELECT rank, pl, p AS ph FROM a{k} JOIN p{k} ON hi = v)",
            f"c{k} AS MATERIALIZED (SELECT rank, pl, ph FROM b{k} WHERE pl <> ph)",
            f"r{k} AS MATERIALIZED (SELECT root, min(rank) AS rank, arg_min(parent, rank) AS parent FROM (SELECT pl AS root, ph AS parent, rank FROM c{k} UNION ALL SELECT ph, pl, rank FROM c{k}) GROUP BY root)",
            f"h{k} AS MATERIALIZED (SELECT x.root, x.rank, x.parent, coalesce(y.parent = x.root AND x.root < x.parent, false) AS undone FROM r{k} x LEFT JOIN r{k} y ON x.parent = y.root)",
            f"m{k}_0 AS MATERIALIZED (SELECT root AS v, parent AS p FROM h{k} WHERE NOT undone)",
            *(f"m{k}_{d + 1} AS MATERIALIZED (SELECT x.v, coalesce(y.p, x.p) AS p FROM m{k}_{d} x LEFT JOIN m{k}_{d} y ON x.p = y.v)" for d in range(doublings)),
            f"p{k + 1} AS MATERIALIZED (SELECT x.v, coalesce(m.p, x.p) AS p FROM p{k} x LEFT JOIN m{k}_{doublings} m ON x.p = m.v)",
        ]
    out.append("f AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT rank, {k + 1} AS round FROM h{k} WHERE NOT undone" for k in range(rounds)) + ")")
    return ", ".join(out)


def forest(edges: str, rounds: int = 9) -> str:
    return f"WITH {forest_ctes(edges, rounds)} SELECT lo, hi, w FROM f JOIN e USING (rank)"


def components(edges: str) -> str:
    return f"WITH {forest_ctes(edges)} SELECT v, min(v) OVER (PARTITION BY p) AS component FROM p9"
