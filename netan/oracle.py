"""SQL for DuckDB that computes what the queries compute, written apart from the Spark code and mostly by other algorithms."""

from __future__ import annotations

FIXTURES = {
    "copurchase": "SELECT a.l_partkey AS src, b.l_partkey AS dst, count(DISTINCT a.l_orderkey)::DOUBLE AS weight FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2",
    "copurchase2": "SELECT a.l_partkey AS src, b.l_partkey AS dst, count(DISTINCT a.l_orderkey)::DOUBLE AS weight FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2 HAVING count(DISTINCT a.l_orderkey) >= 2",
    "supply": "SELECT DISTINCT l_partkey AS src, l_suppkey + 10000000 AS dst, 1.0::DOUBLE AS weight FROM lineitem",
    "trade": "SELECT DISTINCT o_custkey AS src, l_suppkey + 10000000 AS dst, 1.0::DOUBLE AS weight FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "cosupply": "SELECT a.l_suppkey AS src, b.l_suppkey AS dst, count(DISTINCT a.l_orderkey)::DOUBLE AS weight FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_suppkey < b.l_suppkey GROUP BY 1, 2",
    "handoff": "SELECT DISTINCT src, dst, 1.0::DOUBLE AS weight FROM (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL AND src <> dst",
    "coactivity": "SELECT a.u AS src, b.u AS dst, count(*)::DOUBLE AS weight FROM (SELECT DISTINCT epoch_us(ts) // 600000000 AS s, user_id AS u FROM events) a JOIN (SELECT DISTINCT epoch_us(ts) // 600000000 AS s, user_id AS u FROM events) b ON a.s = b.s AND a.u < b.u GROUP BY 1, 2",
    "covalue": "SELECT a.user_id AS src, b.user_id AS dst, count(DISTINCT (a.event_type, a.value))::DOUBLE AS weight FROM events a JOIN events b ON a.event_type = b.event_type AND a.value = b.value AND a.user_id < b.user_id GROUP BY 1, 2",
    "chat": "SELECT a.conv_id * 1000 + a.turn AS src, b.conv_id * 1000 + b.turn AS dst, 1.0::DOUBLE AS weight FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1",
    "geo": "SELECT n_regionkey::BIGINT AS src, n_nationkey::BIGINT + 1000 AS dst, 1.0::DOUBLE AS weight FROM nation UNION ALL SELECT c_nationkey + 1000, c_custkey + 1000000, 1.0 FROM customer UNION ALL SELECT s_nationkey + 1000, s_suppkey + 50000000, 1.0 FROM supplier",
    "sharedline": "WITH l AS (SELECT DISTINCT doc_id, trim(x, ' ') AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x FROM documents) WHERE length(trim(x, ' ')) >= 20), k AS (SELECT line FROM l GROUP BY 1 HAVING count(*) BETWEEN 2 AND 50) SELECT a.doc_id AS src, b.doc_id AS dst, count(*)::DOUBLE AS weight FROM l a JOIN k USING (line) JOIN l b ON b.line = a.line AND a.doc_id < b.doc_id GROUP BY 1, 2",
    "hyperlink": "WITH l AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS link FROM pages), r AS (SELECT link, dense_rank() OVER (ORDER BY link) + 1000000 AS dst FROM (SELECT DISTINCT link FROM l)) SELECT page_id AS src, dst::BIGINT AS dst, 1.0::DOUBLE AS weight FROM l JOIN r USING (link)",
    "nearest": "WITH n AS (SELECT a.vec_id AS a, b.vec_id AS b, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_dot_product(a.e, b.e) / (a.n * b.n), 9) DESC, b.vec_id) AS r FROM (SELECT vec_id, embedding::DOUBLE[] AS e, sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])) AS n FROM embeddings) a JOIN (SELECT vec_id, embedding::DOUBLE[] AS e, sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])) AS n FROM embeddings) b ON a.vec_id <> b.vec_id) SELECT least(a, b) AS src, greatest(a, b) AS dst, count(*)::DOUBLE AS weight FROM n WHERE r <= 8 GROUP BY 1, 2",
    "sharedline_star": "WITH l AS (SELECT DISTINCT doc_id, trim(x, ' ') AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x FROM documents) WHERE length(trim(x, ' ')) >= 20), h AS (SELECT line, min(doc_id) AS hub FROM l GROUP BY 1) SELECT hub AS src, doc_id AS dst, count(*)::DOUBLE AS weight FROM l JOIN h USING (line) WHERE hub <> doc_id GROUP BY 1, 2",
    "colink": "WITH l AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS link FROM pages) SELECT a.page_id AS src, b.page_id AS dst, count(*)::DOUBLE AS weight FROM l a JOIN l b ON a.link = b.link AND a.page_id < b.page_id GROUP BY 1, 2",
}


def edges(name: str) -> str:
    return f"SELECT src, dst, weight FROM ({FIXTURES[name]})"


def _with(name: str, *ctes: str, recursive: bool = False, mirrored: bool = True) -> str:
    """Head of a query over e0 (edges as they are), e (as messages run: both ways if mirrored) and v (vertices)."""
    e = "SELECT src, dst, weight FROM e0 UNION SELECT dst, src, weight FROM e0" if mirrored else "SELECT src, dst, weight FROM e0"
    parts = [f"e0 AS MATERIALIZED ({edges(name)})", f"e AS MATERIALIZED ({e})", "v AS MATERIALIZED (SELECT src AS id FROM e0 UNION SELECT dst FROM e0)", *ctes]
    return ("WITH RECURSIVE " if recursive else "WITH ") + ",\n".join(parts)


COMPONENTS = "cc(id, component) USING KEY (id) AS (SELECT id, id FROM v UNION SELECT e.dst, min(cc.component) FROM cc JOIN e ON cc.id = e.src JOIN recurring.cc AS r ON r.id = e.dst WHERE cc.component < r.component GROUP BY e.dst)"


def components(name: str, select: str = "SELECT id, component FROM cc") -> str:
    return _with(name, COMPONENTS, recursive=True) + "\n" + select


def component_updates(name: str, steps: int) -> str:
    """(superstep, changed) of synchronous least-label propagation."""
    ctes, select = ["s0 AS MATERIALIZED (SELECT id, id AS l FROM v)"], []
    for k in range(1, steps + 1):
        ctes.append(f"s{k} AS MATERIALIZED (SELECT p.id, least(p.l, min(q.l)) AS l FROM s{k - 1} p JOIN e ON e.dst = p.id JOIN s{k - 1} q ON q.id = e.src GROUP BY p.id, p.l)")
        select.append(f"SELECT {k} AS superstep, count(*) AS changed FROM s{k - 1} a JOIN s{k} b USING (id) WHERE a.l <> b.l")
    return _with(name, *ctes) + "\n" + " UNION ALL ".join(select)


def _hash(*parts: str) -> str:
    return "('0x' || substr(md5(concat_ws(':', " + ", ".join(parts) + ")), 1, 8))::BIGINT"


def labels(name: str, steps: int, tie: str = "min", init: str = "self", seed: int = 1, count: str = "count(*)") -> list[str]:
    """CTEs s0..sn of synchronous label propagation."""
    first = {"self": "SELECT id, id AS l FROM v", "min_neighbour": "SELECT src AS id, min(dst) AS l FROM e GROUP BY 1", "random_neighbour": f"SELECT src AS id, arg_min(dst, {{'h': {_hash(repr(str(seed)), 'src', 'dst')}, 'd': dst}}) AS l FROM e GROUP BY 1"}[init]
    ctes = [f"s0 AS MATERIALIZED ({first})"]
    for k in range(1, steps + 1):
        key = {"min": "struct_pack(c := c, n := -l)", "random": f"struct_pack(c := c, h := {_hash(repr(str(seed)), repr(str(k)), 'id', 'l')}, n := -l)", "keep": "struct_pack(c := c, k := (l = own)::INT, n := -l)"}[tie]
        ctes.append(f"h{k} AS MATERIALIZED (SELECT e.dst AS id, q.l, o.l AS own, {count} AS c FROM e JOIN s{k - 1} q ON q.id = e.src JOIN s{k - 1} o ON o.id = e.dst GROUP BY 1, 2, 3)")
        ctes.append(f"s{k} AS MATERIALIZED (SELECT id, arg_max(l, {key}) AS l FROM h{k} GROUP BY id)")
    return ctes


def communities(name: str, steps: int, tie: str = "min", init: str = "self", seed: int = 1, select: str | None = None, extra: tuple[str, ...] = (), count: str = "count(*)") -> str:
    return _with(name, *labels(name, steps, tie, init, seed, count), *extra) + "\n" + (select or f"SELECT id, l AS community FROM s{steps}")


def sweeps(name: str, count: int, classes: int = 2, seed: int = 7, side: str | None = None, select: str = "SELECT id, l AS community FROM {last}") -> str:
    """Class sweeps with least-label ties; side: the class of a vertex, where it is not by hash."""
    ctes, last = ["s0 AS MATERIALIZED (SELECT id, id AS l FROM v)"], "s0"
    for s in range(1, count + 1):
        for c in range(classes):
            now = f"s{s}_{c}"
            ctes.append(f"h{now} AS MATERIALIZED (SELECT e.dst AS id, q.l, count(*) AS c FROM e JOIN {last} q ON q.id = e.src WHERE {side or f"{_hash(repr(str(seed)), repr(str(s)), 'e.dst')} % {classes}"} = {c} GROUP BY 1, 2)")
            ctes.append(f"{now} AS MATERIALIZED (SELECT p.id, coalesce(b.l, p.l) AS l FROM {last} p LEFT JOIN (SELECT id, arg_max(l, struct_pack(c := c, n := -l)) AS l FROM h{now} GROUP BY id) b USING (id))")
            last = now
    return _with(name, *ctes) + "\n" + select.replace("{last}", last)


def label_changes(name: str, steps: int) -> str:
    select = [f"SELECT {k} AS superstep, count(*) AS changed FROM s{k - 1} a JOIN s{k} b USING (id) WHERE a.l <> b.l" for k in range(1, steps + 1)]
    return communities(name, steps, select=" UNION ALL ".join(select))


def ranks(name: str, steps: int, directed: bool = True, spread: bool = False, restart: str | None = None) -> list[str]:
    """CTEs r0..rn of power iteration, jump 0.15."""
    ctes = ["g AS MATERIALIZED (SELECT src, 1.0 / count(*) AS share FROM e GROUP BY 1)", "r0 AS MATERIALIZED (SELECT id, 1.0::DOUBLE AS s FROM v)"]
    r = restart or "1.0"
    for k in range(1, steps + 1):
        lost = f"(SELECT coalesce(sum(s), 0) / (SELECT count(*) FROM v) FROM r{k - 1} WHERE id NOT IN (SELECT src FROM g))" if spread else "0.0"
        ctes.append(f"r{k} AS MATERIALIZED (SELECT v.id, 0.15 * {r} + 0.85 * (coalesce(m.s, 0.0) + {lost}) AS s FROM v LEFT JOIN (SELECT e.dst AS id, sum(p.s * g.share) AS s FROM e JOIN g USING (src) JOIN r{k - 1} p ON p.id = e.src GROUP BY 1) m USING (id))")
    return ctes


def pagerank(name: str, steps: int = 10, directed: bool = True, spread: bool = False, restart: str | None = None, select: str | None = None) -> str:
    return _with(name, *ranks(name, steps, directed, spread, restart), mirrored=not directed) + "\n" + (select or f"SELECT id, round(s, 6) AS score FROM r{steps}")


def pagerank_limit(name: str) -> str:
    """The fixed point, by many steps."""
    return pagerank(name, 130, select="SELECT id, round(s, 6) AS score FROM r130")


LOCAL = (
    "d AS MATERIALIZED (SELECT src AS id, count(*) AS degree FROM e GROUP BY 1)",
    "x AS MATERIALIZED (SELECT a.src AS p, a.dst AS q, b.dst AS r FROM e a JOIN e b ON a.dst = b.src WHERE a.src < a.dst AND a.dst < b.dst AND EXISTS (SELECT 1 FROM e c WHERE c.src = a.src AND c.dst = b.dst))",
    "t AS MATERIALIZED (SELECT id, count(*) AS t FROM (SELECT unnest([p, q, r]) AS id FROM x) GROUP BY 1)",
    "c AS MATERIALIZED (SELECT id, degree, coalesce(t, 0) AS triangles, CASE WHEN degree >= 2 THEN coalesce(t, 0) / (degree * (degree - 1) / 2) END AS coefficient FROM d LEFT JOIN t USING (id))",
)


def clustering(name: str, select: str) -> str:
    # weights may differ by direction in no fixture, so e holds each arc once
    return _with(name, *LOCAL) + "\n" + select


LOCAL_ROWS = "SELECT id, degree, triangles, round(coefficient, 6) AS coefficient FROM c"
AVERAGE = "SELECT round(avg(coefficient), 6) AS coefficient FROM c"
GLOBAL = "SELECT round(sum(triangles) / sum(degree * (degree - 1) // 2), 6) AS coefficient FROM c"
TRIANGLES = "SELECT (sum(triangles) // 3)::BIGINT AS triangles FROM c"


def sampled(name: str, samples: int, seed: int = 1, weight: str = "1", epsilon: float | None = None) -> str:
    h = lambda k, what: _hash(repr(str(seed)), k, repr(what))
    ctes = (
        "d AS MATERIALIZED (SELECT src AS id, count(*) AS degree, list(dst ORDER BY dst) AS nbrs FROM e GROUP BY 1 HAVING count(*) >= 2)",
        f"w AS MATERIALIZED (SELECT id, degree, nbrs, coalesce(sum({weight}) OVER (ORDER BY id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before, ({weight})::BIGINT AS weight FROM d)",
        f"k AS MATERIALIZED (SELECT k, {h('k', 'v')} % (SELECT sum(weight)::BIGINT FROM w) AS at FROM range({samples}) r(k))",
        f"p AS MATERIALIZED (SELECT k, nbrs, {h('k', 'i')} % degree AS i, {h('k', 'j')} % (degree - 1) AS j FROM k ASOF JOIN w ON k.at >= w.before)",
        "q AS MATERIALIZED (SELECT nbrs[i + 1] AS a, nbrs[j + (CASE WHEN j >= i THEN 1 ELSE 0 END) + 1] AS b FROM p)",
    )
    return _with(name, *ctes) + f"\nSELECT round(count(e.src) / count(*), 6) AS coefficient, count(*) AS samples, count(e.src) AS links, {"NULL" if epsilon is None else epsilon}::DOUBLE AS epsilon FROM q LEFT JOIN e ON e.src = a AND e.dst = b"


def fixed_pairs(name: str, pairs: int, seed: int = 1) -> str:
    h = lambda k, what: _hash(repr(str(seed)), k, repr(what))
    ctes = (
        f"d AS MATERIALIZED (SELECT src AS id, count(*) AS degree, list(dst ORDER BY dst) AS nbrs FROM e GROUP BY 1 HAVING count(*) >= 2)",
        f"k AS MATERIALIZED (SELECT id * {pairs} + p AS k, degree, nbrs FROM d, range({pairs}) r(p))",
        f"p AS MATERIALIZED (SELECT nbrs, {h('k', 'i')} % degree AS i, {h('k', 'j')} % (degree - 1) AS j FROM k)",
        "q AS MATERIALIZED (SELECT nbrs[i + 1] AS a, nbrs[j + (CASE WHEN j >= i THEN 1 ELSE 0 END) + 1] AS b FROM p)",
    )
    return _with(name, *ctes) + "\nSELECT round(count(e.src) / count(*), 6) AS coefficient, count(*) AS samples, count(e.src) AS links FROM q LEFT JOIN e ON e.src = a AND e.dst = b"


def overview(name: str) -> str:
    ctes = ("u AS MATERIALIZED (SELECT DISTINCT src, dst FROM e)", "d AS (SELECT src, count(*) AS d FROM u GROUP BY 1)")
    return _with(name, *ctes) + "\nSELECT count(*) AS n, (SELECT count(*) FROM e0) AS m, max(d) AS dmax, sum(d * (d - 1) // 2)::BIGINT AS wedges FROM d"


def _steps(steps: int) -> list[str]:
    """CTEs s0..sn of least labels, and fk: the vertices whose label has changed in step k (f0: all)."""
    ctes = ["s0 AS MATERIALIZED (SELECT id, id AS l FROM v)", "f0 AS MATERIALIZED (SELECT id FROM v)"]
    for k in range(1, steps + 1):
        ctes.append(f"s{k} AS MATERIALIZED (SELECT p.id, least(p.l, min(q.l)) AS l FROM s{k - 1} p JOIN e ON e.dst = p.id JOIN s{k - 1} q ON q.id = e.src GROUP BY p.id, p.l)")
        ctes.append(f"f{k} AS MATERIALIZED (SELECT a.id FROM s{k - 1} a JOIN s{k} b USING (id) WHERE a.l <> b.l)")
    return ctes


def component_messages(name: str, steps: int, blocks: int = 4) -> str:
    """(superstep, raw, combined, cross): messages of synchronous components, by those who have changed; blocks: id modulo their number."""
    one = [f"SELECT {k} AS superstep, count(*) AS raw, count(DISTINCT dst) AS combined, count(*) FILTER (src % {blocks} <> dst % {blocks}) AS cross FROM e JOIN f{k - 1} f ON f.id = e.src" for k in range(1, steps + 1)]
    return _with(name, *_steps(steps)) + "\n" + " UNION ALL ".join(one)


def label_sums(name: str, steps: int) -> str:
    """(superstep, labels): sum of all labels after each step."""
    return _with(name, *_steps(steps)) + "\n" + " UNION ALL ".join(f"SELECT {k} AS superstep, sum(l)::BIGINT AS labels FROM s{k}" for k in range(1, steps + 1))


def variant_counts(name: str, steps: int) -> str:
    """(fixture, variant, updates, messages) of synchronous pull, message and delta runs for components."""
    updates = "(SELECT count(*) FROM v) + " + " + ".join(f"(SELECT count(DISTINCT dst) FROM e JOIN f{k} f ON f.id = e.src)" for k in range(1, steps))
    pulled = "(SELECT count(*) FROM e) + " + " + ".join(f"(SELECT count(*) FROM e WHERE dst IN (SELECT dst FROM e JOIN f{k} f ON f.id = e.src))" for k in range(1, steps))
    sent = "(SELECT count(*) FROM e) + " + " + ".join(f"(SELECT count(*) FROM e JOIN f{k} f ON f.id = e.src)" for k in range(1, steps))
    rows = [f"SELECT '{name}' AS fixture, '{variant}' AS variant, {updates} AS updates, {messages} AS messages" for variant, messages in (("standard", pulled), ("message", sent), ("delta", sent))]
    return _with(name, *_steps(steps)) + "\n" + " UNION ALL ".join(rows)


def label_period(name: str, steps: int) -> str:
    """(period, flipping) of synchronous label propagation: the least number of steps after which the last labels have stood before."""
    differ = lambda k: f"(SELECT count(*) FROM s{k} a JOIN s{steps} b USING (id) WHERE a.l <> b.l)"
    cases = " ".join(f"WHEN {differ(steps - p)} = 0 THEN {p}" for p in range(1, steps))
    return communities(name, steps, select=f"SELECT CASE {cases} ELSE 0 END AS period, {differ(steps - 1)} AS flipping")


def greatest_reached(name: str) -> str:
    """(id, reached): the greatest id that a vertex reaches along its edges, its own included."""
    top = "top(id, reached) USING KEY (id) AS (SELECT id, id FROM v UNION SELECT e0.src, max(top.reached) FROM top JOIN e0 ON top.id = e0.dst JOIN recurring.top AS r ON r.id = e0.src WHERE top.reached > r.reached GROUP BY e0.src)"
    return _with(name, top, recursive=True) + "\nSELECT id, reached FROM top"


def agreement(name: str, steps: int) -> str:
    """(vertices, same_both, rand) of components and communities after so many steps."""
    both = "m AS MATERIALIZED (SELECT component AS a, l AS b, count(*) AS c FROM cc JOIN s%d USING (id) GROUP BY 1, 2)" % steps
    pairs = "x AS (SELECT (SELECT sum(c) FROM m) AS n, (SELECT sum(c * (c - 1) / 2) FROM m) AS ab, (SELECT sum(c * (c - 1) / 2) FROM (SELECT sum(c) AS c FROM m GROUP BY a)) AS pa, (SELECT sum(c * (c - 1) / 2) FROM (SELECT sum(c) AS c FROM m GROUP BY b)) AS pb)"
    return _with(name, COMPONENTS, *labels(name, steps), both, pairs, recursive=True) + "\nSELECT n::BIGINT AS vertices, ab::BIGINT AS same_both, round((n * (n - 1) / 2 + 2 * ab - pa - pb) / (n * (n - 1) / 2), 6) AS rand FROM x"
