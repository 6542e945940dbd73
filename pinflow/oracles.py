"""DuckDB SQL that recomputes the queries: plain aggregates and a recursive replay of the sequential rules."""

from __future__ import annotations

WORDS = "unnest(string_split_regex(lower(coalesce(text, '')), '[ \\n.,;:!?]+'))"

PINS = {
    "parts_by_order": "SELECT DISTINCT l_orderkey AS net_id, l_partkey AS vertex_id FROM lineitem",
    "orders_by_part": "SELECT DISTINCT l_partkey AS net_id, l_orderkey AS vertex_id FROM lineitem",
    "suppliers_by_order": "SELECT DISTINCT l_orderkey AS net_id, l_suppkey AS vertex_id FROM lineitem",
    "parts_by_supplier": "SELECT DISTINCT l_suppkey AS net_id, l_partkey AS vertex_id FROM lineitem",
    "parts_by_customer": "SELECT DISTINCT o_custkey AS net_id, l_partkey AS vertex_id FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "customers_by_part": "SELECT DISTINCT l_partkey AS net_id, o_custkey AS vertex_id FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "docs_by_word": f"SELECT DISTINCT w AS net_id, doc_id AS vertex_id FROM (SELECT doc_id, {WORDS} AS w FROM documents) WHERE w <> ''",
    "docs_by_line": "SELECT DISTINCT w AS net_id, doc_id AS vertex_id FROM (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS w FROM documents) WHERE w <> ''",
    "users_by_hour_type": "SELECT DISTINCT CAST(date_trunc('hour', ts) AS VARCHAR) || event_type AS net_id, user_id AS vertex_id FROM events",
    "users_by_hour": "SELECT DISTINCT CAST(date_trunc('hour', ts) AS VARCHAR) AS net_id, user_id AS vertex_id FROM events",
    "pages_by_link": "SELECT DISTINCT w AS net_id, page_id AS vertex_id FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS w FROM pages)",
    "convs_by_word": f"SELECT DISTINCT w AS net_id, conv_id AS vertex_id FROM (SELECT conv_id, {WORDS} AS w FROM conversations) WHERE w <> ''",
    "signed_clauses": "SELECT DISTINCT l_orderkey AS net_id, l_partkey AS vertex_id FROM lineitem",
}

KNN = """SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM (
 SELECT x.vec_id AS a, y.vec_id AS b, row_number() OVER (PARTITION BY x.vec_id ORDER BY list_cosine_similarity(CAST(x.embedding AS DOUBLE[]), CAST(y.embedding AS DOUBLE[])) DESC, y.vec_id) AS r
 FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) WHERE r <= 5"""
COPURCHASE = "SELECT a.vertex_id AS src, b.vertex_id AS dst, CAST(count(*) AS DOUBLE) AS weight FROM raw a JOIN raw b ON a.net_id = b.net_id AND a.vertex_id < b.vertex_id GROUP BY ALL"


def base(name: str, tag: str = "") -> str:
    """CTEs raw (all pins), p (nets of two pins at least), v (vertices with seq from 0)."""
    t = tag
    return f"""raw{t} AS MATERIALIZED ({PINS[name]}),
p{t} AS MATERIALIZED (SELECT net_id, vertex_id FROM (SELECT *, count(*) OVER (PARTITION BY net_id) AS s FROM raw{t}) WHERE s >= 2),
v{t} AS MATERIALIZED (SELECT vertex_id, row_number() OVER (ORDER BY vertex_id) - 1 AS seq FROM (SELECT DISTINCT vertex_id FROM raw{t}))"""


def bound(total: str, k: int, eps_percent: int = 3) -> str:
    """ceil((100 + eps) * total / (100 * k)) in whole numbers."""
    return f"(({100 + eps_percent} * {total} + {100 * k - 1}) // {100 * k})"


def strength(k: int, n: str, m: str, gamma: float = 1.5, scale: float = 1.0) -> str:
    return f"(CAST({gamma} AS DOUBLE) * ((sqrt(CAST({k} AS DOUBLE)) * {m} / (CAST({n} AS DOUBLE) * sqrt(CAST({n} AS DOUBLE)))) * CAST({scale} AS DOUBLE)))"


def _pen(gamma: float, x: str) -> str:
    return f"sqrt(CAST({x} AS DOUBLE))" if gamma == 1.5 else "CAST(1 AS DOUBLE)" if gamma == 1 else f"CAST({x} AS DOUBLE)"


def _argmax(blocks: str, fits: str, score: str, load: str = "load[j + 1]") -> str:
    """The j of the best score; equal scores go to the lighter, then the smaller one."""
    return f"CAST(-(list_max(list_transform(list_filter({blocks}, lambda j: {fits}), lambda j: {{'s': {score}, 'l': -({load}), 'i': -j}})).i) AS INTEGER)"


def replay(k: int, objective: str = "con", gamma: float = 1.5, scale: float = 1.0, rule: str = "greedy", graph: bool = False, pins: str = "p", vertices: str = "v", weight: str = "1.0", vertex_weight: str = "1", weighted: bool = False, tag: str = "", ell: int = 5, minima: int = 4, fanout: int = 4, growing: bool = False) -> str:
    """CTEs ending in a{tag} (seq, vertex_id, block, touched, evaluated). graph: pins is e(src, dst).

    rule: 'greedy'; 'minmax' (all blocks of a net), 'capped' (its ell latest different blocks); 'signature'; 'sections' (k is a
    multiple of fanout: two levels). growing: bound and strength follow the arrivals so far. touched and evaluated are of the
    greedy rule: blocks with votes, and scores that the split engine computes. The walk carries the placed blocks in order and the loads; what a net remembers is read
    off the blocks of its earlier pins. Tables are materialised: each step of the recursion reads them again."""
    t = tag
    if graph:
        arrivals = f"SELECT b.seq, [a.seq] AS before, CAST(1 AS DOUBLE) AS w FROM (SELECT src AS x, dst AS y FROM {pins} UNION ALL SELECT dst, src FROM {pins}) JOIN {vertices} a ON a.vertex_id = x JOIN {vertices} b ON b.vertex_id = y WHERE a.seq < b.seq"
        nets = f"(SELECT count(*) FROM {pins})"
    else:
        arrivals = f"SELECT a.seq, list(b.seq ORDER BY b.seq) AS before, any_value(a.w) AS w FROM q{t} a JOIN q{t} b ON a.net_id = b.net_id AND b.seq < a.seq GROUP BY a.seq, a.net_id"
        nets = f"(SELECT sum(w) FROM (SELECT net_id, any_value(w) AS w FROM q{t} GROUP BY net_id))" if weighted else f"(SELECT count(DISTINCT net_id) FROM {pins})"
    total = f"(SELECT CAST(sum(c) AS BIGINT) FROM u{t})"
    met = "list_reverse(list_transform(x.before, lambda y: w.a[y + 1]))"  # blocks of a net's earlier pins, latest first
    named = "[]"
    if rule == "signature":
        lasts = "[]"
        named = f"coalesce((SELECT list(DISTINCT CAST('0x' || substr(sig, 1, 8) AS BIGINT) % {k}) FROM (SELECT i.range, min(md5(i.range || ':' || net_id)) AS sig FROM q{t} z, range({minima}) i WHERE z.seq = u.seq GROUP BY i.range)), [])"
    elif rule == "minmax":
        lasts = f"list_transform(s.nets, lambda x: {{'b': list_distinct({met}), 'w': x.w}})"
    elif rule == "capped":
        lasts = f"list_transform(s.nets, lambda x: {{'b': list_filter(list_distinct({met}), lambda z: len(list_distinct({met}[1:list_position({met}, z) - 1])) < {ell}), 'w': x.w}})"
    else:
        open_nets = "s.nets" if objective == "con" else "list_filter(s.nets, lambda x: len(list_distinct(list_transform(x.before, lambda y: w.a[y + 1]))) = 1)"
        lasts = f"list_transform({open_nets}, lambda x: {{'b': [w.a[x.before[-1] + 1]], 'w': x.w}})"
    votes = "coalesce(list_sum(list_transform(list_filter(lasts, lambda x: list_contains(x.b, j)), lambda x: x.w)), 0)"
    room, every = "load[j + 1] + c <= h.cap", f"range({k})"
    greedy = f"{votes} - (h.g * c) * {_pen(gamma, 'load[j + 1]')}"
    layer = ""
    if rule == "signature":
        block = _argmax(every, "true", f"CASE WHEN list_contains(named, j) AND {room} THEN 1 ELSE 0 END")
    elif rule in ("minmax", "capped"):
        block = _argmax(every, f"{room} AND load[j + 1] <= list_min(load) + h.slack", votes)
    elif rule == "sections":
        leaves = k // fanout
        filled = f"(CAST(list_sum(load[j * {leaves} + 1 : (j + 1) * {leaves}]) AS DOUBLE) / {leaves})"
        pull = f"coalesce(list_sum(list_transform(list_filter(lasts, lambda x: x.b[1] // {leaves} = j), lambda x: x.w)), 0)"
        layer = _argmax(f"range({fanout})", f"{filled} * {leaves} + c <= h.cap * {leaves}", f"{pull} - c * (h.g * sqrt({filled}))", filled)
        block = _argmax(every, f"{room} AND j // {leaves} = part", f"{votes} - c * (h.g * sqrt(CAST(load[j + 1] AS DOUBLE)))")
    else:
        block = _argmax(every, room, greedy)
    touched = "list_distinct(list_transform(lasts, lambda x: x.b[1]))"
    light = "(list_position(load, list_min(load)) - 1)"
    effort = f"len({touched}) AS touched, len(list_filter({touched}, lambda j: {room})) + CASE WHEN NOT list_contains({touched}, {light}) AND list_min(load) + c <= h.cap THEN 1 ELSE 0 END AS evaluated" if rule == "greedy" else "0 AS touched, 0 AS evaluated"
    limits = f"SELECT {bound(total, k)} AS cap, {strength(k, total if weighted else f'(SELECT count(*) FROM u{t})', nets, gamma, scale)} AS g, greatest(1, {bound(f'(SELECT count(*) FROM u{t})', k)} - ((SELECT count(*) FROM u{t}) + {k - 1}) // {k}) AS slack"
    if growing:
        limits = f"SELECT seq, {bound('(seq + 1)', k)} AS cap, {strength(k, '(seq + 1)', 'greatest(1, met)')} AS g FROM (SELECT u.seq, (SELECT count(DISTINCT z.net_id) FROM q{t} z WHERE z.seq < u.seq) AS met FROM u{t} u)"
    source = f"SELECT s.seq, s.vertex_id, s.c, s.named, w.a, w.load, {lasts} AS lasts FROM w{t} w JOIN s{t} s ON s.seq = w.seq + 1"
    if layer:
        source = f"SELECT y.*, {layer} AS part FROM ({source}) y, h{t} h"
    q = "" if graph else f"q{t} AS MATERIALIZED (SELECT v.seq, p.net_id, CAST({weight} AS DOUBLE) AS w FROM {pins} p JOIN {vertices} v USING (vertex_id)),\n"
    return f"""{q}u{t} AS MATERIALIZED (SELECT seq, vertex_id, {vertex_weight} AS c FROM {vertices}),
b{t} AS MATERIALIZED ({arrivals}),
s{t} AS MATERIALIZED (SELECT n.*, {named.replace('u.seq', 'n.seq')} AS named FROM (SELECT u.seq, u.vertex_id, u.c, coalesce(list({{'before': b.before, 'w': b.w}}) FILTER (b.before IS NOT NULL), []) AS nets FROM u{t} u LEFT JOIN b{t} b USING (seq) GROUP BY ALL) n),
h{t} AS MATERIALIZED ({limits}),
w{t} AS (SELECT CAST(-1 AS BIGINT) AS seq, CAST(-1 AS BIGINT) AS vertex_id, CAST([] AS INTEGER[]) AS a, list_transform(range({k}), lambda x: CAST(0 AS BIGINT)) AS load, -1 AS block, CAST(0 AS BIGINT) AS touched, CAST(0 AS BIGINT) AS evaluated
 UNION ALL
 SELECT seq, vertex_id, list_append(a, block), list_transform(load, lambda x, i: x + CASE WHEN i - 1 = block THEN c ELSE 0 END), block, touched, evaluated FROM (
  SELECT r.seq, vertex_id, a, load, c, {block} AS block, {effort} FROM ({source}) r, h{t} h{' WHERE h.seq = r.seq' if growing else ''})),
a{t} AS MATERIALIZED (SELECT seq, vertex_id, block, touched, evaluated FROM w{t} WHERE seq >= 0)"""


def edge_replay(k: int) -> str:
    """CTEs ending in a (seq, src, dst, block): the edge-at-a-time rule over e(src, dst); blocks that hold both ends, else one, else any."""
    ends = lambda x: f"(SELECT coalesce(list(o.seq), []) FROM o WHERE o.seq < n.seq AND (o.src = n.{x} OR o.dst = n.{x}))"
    held = lambda x: f"list_distinct(list_transform({x}, lambda y: w.a[y + 1]))"
    best = lambda own: f"list_min(list_transform(list_filter({own}, lambda j: load[j + 1] < cap), lambda j: {{'l': load[j + 1], 'i': j}})).i"
    return f"""o AS MATERIALIZED (SELECT row_number() OVER (ORDER BY src, dst) - 1 AS seq, src, dst FROM e),
s AS MATERIALIZED (SELECT n.seq, n.src, n.dst, {ends('src')} AS x, {ends('dst')} AS y, {bound('(SELECT count(*) FROM o)', k)} AS cap FROM o n),
w AS (SELECT CAST(-1 AS BIGINT) AS seq, CAST(0 AS BIGINT) AS src, CAST(0 AS BIGINT) AS dst, CAST([] AS INTEGER[]) AS a, list_transform(range({k}), lambda x: CAST(0 AS BIGINT)) AS load, -1 AS block
 UNION ALL
 SELECT seq, src, dst, list_append(a, block), list_transform(load, lambda z, i: z + CASE WHEN i - 1 = block THEN 1 ELSE 0 END), block FROM (
  SELECT seq, src, dst, a, load, CAST(coalesce({best('list_intersect(p, q)')}, {best('list_distinct(list_concat(p, q))')}, {best(f'range({k})')}) AS INTEGER) AS block FROM (
   SELECT s.seq, s.src, s.dst, s.cap, w.a, w.load, {held('s.x')} AS p, {held('s.y')} AS q FROM w JOIN s ON s.seq = w.seq + 1))),
a AS MATERIALIZED (SELECT seq, src, dst, block FROM w WHERE seq >= 0)"""


def spread(k: int, iters: int) -> str:
    """CTEs ending in l{iters} (vertex_id, block): label propagation from even shares, ``iters`` rounds within the bound."""
    out = [f"z AS MATERIALIZED (SELECT net_id, count(*) AS size FROM p GROUP BY net_id)", f"g AS MATERIALIZED (SELECT {bound('(SELECT count(*) FROM v)', k)} AS cap)", f"l0 AS MATERIALIZED (SELECT vertex_id, CAST(seq % {k} AS INTEGER) AS block FROM v)"]
    for i in range(iters):
        out += [
            f"e{i} AS MATERIALIZED (SELECT net_id, block, count(*) / CAST(any_value(size) AS DOUBLE) AS w FROM p JOIN l{i} USING (vertex_id) JOIN z USING (net_id) GROUP BY net_id, block)",
            f"t{i} AS MATERIALIZED (SELECT vertex_id, block, round(sum(w), 9) AS w FROM p JOIN e{i} USING (net_id) GROUP BY vertex_id, block)",
            f"x{i} AS MATERIALIZED (SELECT vertex_id, block AS want FROM t{i} QUALIFY row_number() OVER (PARTITION BY vertex_id ORDER BY w DESC, block) = 1)",
            f"y{i} AS MATERIALIZED (SELECT l.vertex_id, x.want, row_number() OVER (PARTITION BY x.want ORDER BY v.seq) - 1 AS r FROM l{i} l JOIN x{i} x USING (vertex_id) JOIN v USING (vertex_id) WHERE x.want <> l.block)",
            f"f{i} AS MATERIALIZED (SELECT j.range AS block, (SELECT cap FROM g) - (SELECT count(*) FROM l{i} WHERE block = j.range) AS room FROM range({k}) j)",
            f"l{i + 1} AS MATERIALIZED (SELECT l.vertex_id, CASE WHEN y.r < f.room THEN y.want ELSE l.block END AS block FROM l{i} l LEFT JOIN y{i} y USING (vertex_id) LEFT JOIN f{i} f ON f.block = y.want)",
        ]
    return ",\n".join(out)


def rounds(k: int, ends: list[int], objective: str = "con", tag: str = "") -> str:
    """CTEs ending in d{tag} (seq, vertex_id, block): batches that end before ``ends`` decide against the state before them.

    Per batch: votes of nets' latest earlier pins, wishes that beat the lightest block, taken by arrival while there is room;
    the rest goes to the free places of blocks from the lowest level up."""
    t = tag
    n, m = "(SELECT count(*) FROM v)", "(SELECT count(DISTINCT net_id) FROM p)"
    out = [f"q{t} AS MATERIALIZED (SELECT v.seq, p.net_id FROM p JOIN v USING (vertex_id))", f"h{t} AS MATERIALIZED (SELECT {bound(n, k)} AS cap, {strength(k, n, m)} AS g)", f"d{t}_0 AS MATERIALIZED (SELECT CAST(0 AS BIGINT) AS seq, CAST(0 AS INTEGER) AS block WHERE false)"]
    first = 0
    for i, end in enumerate(ends):
        d, x = f"d{t}_{i}", f"{t}_{i}"
        shut = f" AND net_id NOT IN (SELECT net_id FROM q{t} JOIN {d} USING (seq) GROUP BY net_id HAVING min(block) <> max(block))" if objective == "cut" else ""
        out += [
            f"l{x} AS MATERIALIZED (SELECT j.range AS block, (SELECT count(*) FROM {d} WHERE block = j.range) AS load FROM range({k}) j)",
            f"o{x} AS MATERIALIZED (SELECT net_id, arg_max(block, seq) AS block FROM q{t} JOIN {d} USING (seq) WHERE true{shut} GROUP BY net_id)",
            f"n{x} AS MATERIALIZED (SELECT q.seq, o.block, count(*) AS votes FROM q{t} q JOIN o{x} o USING (net_id) WHERE q.seq >= {first} AND q.seq < {end} GROUP BY ALL)",
            f"c{x} AS MATERIALIZED (SELECT n.seq, n.block, n.votes - h.g * sqrt(CAST(l.load AS DOUBLE)) AS score, l.load FROM n{x} n JOIN l{x} l USING (block), h{t} h WHERE l.load + 1 <= h.cap)",
            f"r{x} AS MATERIALIZED (SELECT block, load, -h.g * sqrt(CAST(load AS DOUBLE)) AS score FROM l{x}, h{t} h ORDER BY load, block LIMIT 1)",
            f"w{x} AS MATERIALIZED (SELECT seq, block FROM (SELECT c.seq, c.block, c.score, c.load, r.score AS rs, r.load AS rl, r.block AS rb FROM c{x} c, r{x} r QUALIFY row_number() OVER (PARTITION BY c.seq ORDER BY c.score DESC, c.load, c.block) = 1) WHERE (score, -load, -block) > (rs, -rl, -rb))",
            f"k{x} AS MATERIALIZED (SELECT w.seq, w.block FROM (SELECT *, row_number() OVER (PARTITION BY block ORDER BY seq) AS place FROM w{x}) w JOIN l{x} l USING (block), h{t} h WHERE l.load + w.place <= h.cap)",
            f"f{x} AS MATERIALIZED (SELECT j.range AS block, (SELECT count(*) FROM {d} WHERE block = j.range) + (SELECT count(*) FROM k{x} WHERE block = j.range) AS load FROM range({k}) j)",
            f"s{x} AS MATERIALIZED (SELECT f.block, row_number() OVER (ORDER BY z.range, f.block) AS place FROM f{x} f, h{t} h, range((SELECT max(cap) FROM h{t})) z WHERE z.range >= f.load AND z.range < h.cap)",
            f"e{x} AS MATERIALIZED (SELECT seq, row_number() OVER (ORDER BY seq) AS place FROM v WHERE seq >= {first} AND seq < {end} AND seq NOT IN (SELECT seq FROM k{x}))",
            f"d{t}_{i + 1} AS MATERIALIZED (SELECT seq, block FROM {d} UNION ALL SELECT seq, CAST(block AS INTEGER) FROM k{x} UNION ALL SELECT e.seq, CAST(s.block AS INTEGER) FROM e{x} e JOIN s{x} s USING (place))",
        ]
        first = end
    out.append(f"d{t} AS MATERIALIZED (SELECT v.seq, v.vertex_id, d.block FROM d{t}_{len(ends)} d JOIN v USING (seq))")
    return ",\n".join(out)


HASH = "CAST(CAST('0x' || substr(md5(CAST({x} AS VARCHAR)), 1, 8) AS BIGINT) % {k} AS INTEGER)"


def hashed(k: int, x: str = "vertex_id") -> str:
    return HASH.format(x=x, k=k)


def seeded(k: int, seed, x: str = "vertex_id") -> str:
    return f"CAST(CAST('0x' || substr(md5({seed} || ':' || CAST({x} AS VARCHAR)), 1, 8) AS BIGINT) % {k} AS INTEGER)"


def quality(assign: str, pins: str = "p") -> str:
    """cut_net and connectivity of the CTE assign (vertex_id, block)."""
    return f"SELECT CAST(count(*) FILTER (l > 1) AS DOUBLE) AS cut_net, CAST(sum(l - 1) AS DOUBLE) AS connectivity FROM (SELECT net_id, count(DISTINCT block) AS l FROM {pins} JOIN {assign} USING (vertex_id) GROUP BY net_id)"
