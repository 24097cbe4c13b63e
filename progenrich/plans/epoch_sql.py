"""SQL of whole runs, for comparison: the same specification as a chain of common table expressions.

Windows and sorts stand where the engine uses ratios and bins, so the two agree only if both are right.
"""

from __future__ import annotations

from ..functions.tagexpr import parse_tag_expr, predicates
from ..operators.baselines import P_STEPS, PRIME, scorer_order
from ..operators.scorers import LADDER
from ..operators.state import Query
from ..sources.objects import COLLECTIONS
from .workloads import FULL_COST, RunSpec

BASES = {
    "orders": """SELECT o_orderkey AS object_id, o_orderdate, o_custkey, o_totalprice, c_nationkey, n_name, n_regionkey,
        o_orderstatus AS t_status, o_orderpriority AS t_priority, c_mktsegment AS t_segment
        FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey""",
    "lineitem": """SELECT ((l_orderkey * 8 + l_linenumber) * 20011 + l_partkey) * 1009 + l_suppkey AS object_id, l_shipdate, l_quantity, l_discount,
        l_returnflag AS t_returnflag, l_linestatus AS t_linestatus FROM lineitem""",
    "events": """SELECT event_id AS object_id, ts, user_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS location, event_type AS t_kind FROM events""",
    "docs": """SELECT d.doc_id AS object_id, source, n_chars, quality AS t_quality, toxic AS t_toxic, lang AS t_lang FROM documents d JOIN labels l ON d.doc_id = l.doc_id""",
}


def lit(tag) -> str:
    return f"'{tag}'" if isinstance(tag, str) else str(tag)


def noise_sql(key: str, tag_no: int, scorer: int) -> str:
    return f"((7919 * {key} + {31337 * tag_no + 104729 * scorer} + {613 * (13 * scorer + 7 * tag_no + 1)} * ({key} // 97)) % 10007) / 10007.0::DOUBLE"


def raw_sql(key: str, has: str, tag_no: int, scorer: int) -> str:
    w = LADDER[scorer][1]
    return f"(CASE WHEN {has} THEN 1.0::DOUBLE - {w}::DOUBLE * ({noise_sql(key, tag_no, scorer)}) ELSE {w}::DOUBLE * ({noise_sql(key, tag_no, scorer)}) END)"


def h_sql(p: str) -> str:
    return f"(CASE WHEN {p} <= 0 OR {p} >= 1 THEN 0.0::DOUBLE ELSE -({p}) * log2({p}) - (1 - ({p})) * log2(1 - ({p})) END)"


class SpecSql:
    """Names and expressions of one specification."""

    def __init__(self, spec: RunSpec):
        self.spec = spec
        c = COLLECTIONS[spec.collection]
        self.query = Query(parse_tag_expr(spec.expr), c.catalog())
        self.preds = predicates(self.query.expr)
        self.k = len(self.preds)

    def has(self, i: int) -> str:
        p = self.preds[i]
        c = f"{self.query.catalog.type(p.type).truth} = {lit(p.tag)}"
        return c if p.op == "=" else f"NOT ({c})"

    def tag_no(self, i: int) -> int:
        p = self.preds[i]
        return self.query.catalog.type(p.type).number(p.tag)

    def base(self) -> list[str]:
        s = self.spec
        raws = " UNION ALL ".join(f"SELECT object_id, {i} AS pred, {j} AS scorer, {raw_sql('object_id', self.has(i), self.tag_no(i), j)} AS raw, ({self.has(i)}) AS truth, part FROM base" for i in range(self.k) for j in range(4))
        return [
            f"base AS MATERIALIZED (SELECT *, (object_id * 7919) % 10 AS part FROM ({BASES[s.collection]}))",
            f"chosen AS MATERIALIZED (SELECT * FROM base WHERE part >= 2 AND ({s.where}))",
            f"raws AS MATERIALIZED ({raws})",
            "cal AS MATERIALIZED (SELECT pred, scorer, CAST(least(floor(raw * 20), 19) AS INTEGER) AS b, avg(CAST(CAST(truth AS INTEGER) AS DOUBLE)) AS rate FROM raws WHERE part < 2 GROUP BY ALL)",
            """outs AS MATERIALIZED (SELECT r.object_id, r.pred, r.scorer, r.part, coalesce(c.rate, (CAST(least(floor(raw * 20), 19) AS INTEGER) + 0.5) / 20) AS prob
               FROM raws r LEFT JOIN cal c ON r.pred = c.pred AND r.scorer = c.scorer AND c.b = CAST(least(floor(r.raw * 20), 19) AS INTEGER))""",
        ]

    def table(self) -> list[str]:
        q = [x[2] for x in LADDER]

        def p(mask: str) -> str:
            top = " + ".join(f"(CASE WHEN {mask} & {1 << j} > 0 THEN {q[j]}::DOUBLE * f{j} ELSE 0 END)" for j in range(4))
            low = " + ".join(f"(CASE WHEN {mask} & {1 << j} > 0 THEN {q[j]}::DOUBLE ELSE 0 END)" for j in range(4))
            return f"(({top}) / ({low}))"

        costs = ", ".join(f"({j}, {c}::DOUBLE)" for j, (c, _, _) in enumerate(LADDER))
        value = {"avg": "dh", "per_cost": "dh / cost"}.get(self.spec.pick)
        rows = [
            f"f AS MATERIALIZED (SELECT object_id, pred, {', '.join(f'max(prob) FILTER (scorer = {j}) AS f{j}' for j in range(4))} FROM outs WHERE part < 2 GROUP BY object_id, pred)",
            f"costs(scorer, cost) AS (VALUES {costs})",
            f"""hs AS (SELECT f.object_id, f.pred, m.mask, s.scorer, s.cost, {p('m.mask')} AS pa, {p('(m.mask | (1 << s.scorer))')} AS pb
               FROM f, (VALUES (1), (3), (5), (7), (9), (11), (13)) m(mask), costs s WHERE m.mask & (1 << s.scorer) = 0)""",
            f"""red AS MATERIALIZED (SELECT object_id, pred, mask, scorer, cost, CAST(least(floor({h_sql('pa')} * 10), 9) AS INTEGER) AS b, {h_sql('pb')} - {h_sql('pa')} AS dh FROM hs)""",
        ]
        if value:
            pick = f"SELECT pred, mask, b, scorer, dh, n, row_number() OVER (PARTITION BY pred, mask, b ORDER BY floor({value} * 1e9), scorer) AS k FROM (SELECT pred, mask, b, scorer, avg(dh) AS dh, count(*) AS n, min(cost) AS cost FROM src GROUP BY ALL)"
        else:
            pick = """SELECT v.pred, v.mask, v.b, v.scorer, a.dh, a.n, row_number() OVER (PARTITION BY v.pred, v.mask, v.b ORDER BY votes DESC, v.scorer) AS k
                FROM (SELECT pred, mask, b, scorer, count(*) AS votes FROM (SELECT *, row_number() OVER (PARTITION BY object_id, pred, mask, b ORDER BY dh, scorer) AS j FROM src) WHERE j = 1 GROUP BY ALL) v
                JOIN (SELECT pred, mask, b, scorer, avg(dh) AS dh, count(*) AS n FROM src GROUP BY ALL) a USING (pred, mask, b, scorer)"""
        return [*rows, f"cells AS MATERIALIZED (SELECT * FROM (WITH src AS (SELECT * FROM red UNION ALL SELECT object_id, pred, mask, scorer, cost, -1 AS b, dh FROM red) {pick}) WHERE k = 1)"]

    def start(self) -> str:
        """Raw state at the start, from the seed or from stored outputs."""
        q, cols, joins = LADDER, ["c.object_id"], []
        for i in range(self.k):
            joins.append(f"JOIN outs s{i} ON s{i}.object_id = c.object_id AND s{i}.pred = {i} AND s{i}.scorer = 0")
            if self.spec.cached >= 0:
                hit = f"((c.object_id // 7) % 100 < {self.spec.cached})"
                joins.append(f"JOIN outs d{i} ON d{i}.object_id = c.object_id AND d{i}.pred = {i} AND d{i}.scorer = 3")
                cols += [f"CASE WHEN {hit} THEN 9 ELSE 1 END AS m{i}", f"{q[0][2]}::DOUBLE * s{i}.prob + CASE WHEN {hit} THEN {q[3][2]}::DOUBLE * d{i}.prob ELSE 0 END AS ws{i}", f"{q[0][2]}::DOUBLE + CASE WHEN {hit} THEN {q[3][2]}::DOUBLE ELSE 0 END AS qs{i}"]
            else:
                cols += [f"1 AS m{i}", f"{q[0][2]}::DOUBLE * s{i}.prob AS ws{i}", f"{q[0][2]}::DOUBLE AS qs{i}"]
        return f"raw0 AS MATERIALIZED (SELECT {', '.join(cols)} FROM chosen c {' '.join(joins)})"

    def match(self, ps: list[str]) -> str:
        return " * ".join(ps)  # workloads join predicates of different types by AND

    def state(self, e: int) -> list[str]:
        ps = ", ".join(f"ws{i} / qs{i} AS p{i}" for i in range(self.k))
        return [
            f"st{e} AS MATERIALIZED (SELECT *, {self.match([f'p{i}' for i in range(self.k)])} AS P FROM (SELECT *, {ps} FROM raw{e}))",
            f"""lam{e} AS MATERIALIZED (SELECT coalesce(max(s / ({self.spec.alpha} * tot + k)), 0) AS lam, max(tot) AS tot FROM (SELECT sum(P) OVER w AS s, row_number() OVER w AS k, sum(P) OVER () AS tot FROM st{e} WINDOW w AS (ORDER BY P DESC, object_id ROWS UNBOUNDED PRECEDING)))""",
        ]

    def items(self, e: int) -> str:
        """Ranked items of epoch e + 1 from state e: object_id, pred, scorer, cost, key."""
        s, parts = self.spec, []
        if s.approach == "progressive":
            for i in range(self.k):
                start = f"least(greatest(0.5 * (1 + sqrt(greatest(0.0, 1 - pow(he, 4.0::DOUBLE / 3)))), 0.500000001), 1 - 1e-12)"
                step = lambda x: f"least(greatest({x} - ({h_sql(x)} - he) / log2((1 - {x}) / {x}), 0.500000001), 1 - 1e-12)"
                ps = [f"p{j}" if j != i else "pe" for j in range(self.k)]
                deltas = f"""SELECT t.*, {h_sql(f'p{i}')} AS h FROM st{e} t WHERE m{i} <> 15"""
                default = f"(SELECT j FROM (VALUES (0), (1), (2), (3)) d(j) WHERE m{i} & (1 << j) = 0 ORDER BY j LIMIT 1)"
                looked = f"""SELECT t.*, coalesce(a.scorer, b.scorer, CASE WHEN m{i} & 1 = 0 THEN 0 WHEN m{i} & 2 = 0 THEN 1 WHEN m{i} & 4 = 0 THEN 2 ELSE 3 END) AS scorer, least(1.0, greatest(0.0, h + coalesce(a.dh, b.dh, 0))) AS he
                    FROM ({deltas}) t LEFT JOIN cells a ON a.pred = {i} AND a.mask = m{i} AND a.b = CAST(least(floor(h * 10), 9) AS INTEGER) LEFT JOIN cells b ON b.pred = {i} AND b.mask = m{i} AND b.b = -1"""
                del default
                x = f"SELECT *, {start} AS x0 FROM ({looked})"
                for n in range(4):
                    x = f"SELECT *, {step(f'x{n}')} AS x{n + 1} FROM ({x})"
                x = f"SELECT *, CASE WHEN he >= 1 THEN 0.5 WHEN he <= 0 THEN 1.0 ELSE x4 END AS up FROM ({x})"
                x = f"SELECT *, greatest(p{i}, CASE WHEN 1 - up >= p{i} THEN 1 - up ELSE up END) AS pe FROM ({x})"
                parts.append(f"SELECT object_id, {i} AS pred, x.scorer, cost, P, {self.match(ps)} AS E FROM ({x}) x JOIN costs ON costs.scorer = x.scorer")
            rows = " UNION ALL ".join(parts)
            free = f"i{e}r AS MATERIALIZED ({rows})"
            if s.benefit == "relative":
                value = f"SELECT r.*, P * E / cost AS v FROM i{e}r r"
            else:
                a = s.alpha
                solved = f"""SELECT object_id, pred, {1 + a} * greatest(max(CASE WHEN k2 > 0 THEN s2 / (t2 + k2) ELSE 0 END), max((s2 + E) / (t2 + k2 + 1)), max(E / (t2 + 1))) AS fe FROM (
                    SELECT r.object_id, r.pred, r.E, o.s - CASE WHEN own THEN r.P ELSE 0 END AS s2, o.k - CASE WHEN own THEN 1 ELSE 0 END AS k2, {a} * (tot - r.P + r.E) AS t2 FROM (
                      SELECT r.*, o.s, o.k, tot, (o.P < r.P OR (o.P = r.P AND o.object_id >= r.object_id)) AS own FROM i{e}r r, lam{e},
                        (SELECT object_id, P, sum(P) OVER w AS s, row_number() OVER w AS k FROM st{e} WINDOW w AS (ORDER BY P DESC, object_id ROWS UNBOUNDED PRECEDING)) o) r, (SELECT 1) z, LATERAL (SELECT r.s AS s, r.k AS k) o) GROUP BY object_id, pred"""
                gain = "r.P * fe / cost" if s.benefit == "weighted" else f"(fe - {1 + a} * (SELECT lam FROM lam{e})) / cost"
                value = f"SELECT r.*, {gain} AS v FROM i{e}r r JOIN ({solved}) z ON z.object_id = r.object_id AND z.pred = r.pred"
            ranked = f"SELECT object_id, pred, scorer, cost, CAST(floor(v * 1e9) AS BIGINT) AS key, P, E, P <= (SELECT lam FROM lam{e}) AS outside FROM ({value})"
            if s.rule == "all":
                kept = "true"
            else:
                kept = "outside" if s.rule == "outside" else f"outside AND E > (SELECT lam FROM lam{e}) * (1 + {s.alpha} * (E - P))"
            return f"{free}, i{e}a AS MATERIALIZED ({ranked}), i{e} AS MATERIALIZED (SELECT * FROM i{e}a WHERE ({kept}) OR NOT EXISTS (SELECT 1 FROM i{e}a WHERE {kept}))"
        order = scorer_order(self.query)
        left = " UNION ALL ".join(f"SELECT t.object_id, {i} AS pred, {j} AS scorer, {LADDER[j][0]}::DOUBLE AS cost, z.P AS p0, {order[i, j]} AS place FROM st{e} t JOIN st0 z ON z.object_id = t.object_id WHERE t.m{i} & {1 << j} = 0" for i in range(self.k) for j in range(4))
        if s.approach == "scorer_first":
            return f"i{e} AS MATERIALIZED (SELECT *, -(place * {2 * P_STEPS}::BIGINT + ({P_STEPS} - CAST(floor(p0 * {P_STEPS}) AS BIGINT))) AS key FROM ({left}))"
        if s.approach == "object_first":
            return f"i{e} AS MATERIALIZED (SELECT *, CAST(floor(p0 * {P_STEPS}) AS BIGINT) AS key FROM ({left}))"
        n = e + 1
        mix = f"((object_id % {PRIME}) * 7919 + pred * 15485863 + scorer * 32452843 + {n * 49979687 + s.seed * 67867967}) % {PRIME}"
        spread = f"((object_id % {PRIME}) * 104729 + {n * 1299709 + s.seed * 15485863}) % {PRIME}"
        return f"i{e} AS MATERIALIZED (SELECT *, {spread} AS key FROM (SELECT *, row_number() OVER (PARTITION BY object_id ORDER BY {mix}, pred, scorer) AS first FROM ({left})) WHERE first = 1)"

    def epoch(self, e: int) -> list[str]:
        """From state e to raw state e + 1."""
        upd = []
        for i in range(self.k):
            upd += [f"bit_or(CASE WHEN pred = {i} THEN 1 << scorer ELSE 0 END) AS dm{i}", f"sum(CASE WHEN pred = {i} THEN q * prob ELSE 0 END) AS dws{i}", f"sum(CASE WHEN pred = {i} THEN q ELSE 0 END) AS dqs{i}"]
        q = "CASE r.scorer " + " ".join(f"WHEN {j} THEN {LADDER[j][2]}::DOUBLE" for j in range(4)) + " END"
        cols = ", ".join(f"m{i} | coalesce(dm{i}, 0) AS m{i}, ws{i} + coalesce(dws{i}, 0) AS ws{i}, qs{i} + coalesce(dqs{i}, 0) AS qs{i}" for i in range(self.k))
        budget = f"({self.spec.share}::DOUBLE * {FULL_COST} * {self.k} * (SELECT count(*) FROM chosen))"
        return [
            self.items(e),
            f"plan{e} AS MATERIALIZED (SELECT * FROM (SELECT *, sum(cost) OVER (ORDER BY key DESC, object_id, pred, scorer ROWS UNBOUNDED PRECEDING) AS run FROM i{e}) WHERE run - cost < {budget})",
            f"d{e} AS MATERIALIZED (SELECT object_id, {', '.join(upd)} FROM (SELECT r.object_id, r.pred, r.scorer, o.prob, {q} AS q FROM plan{e} r JOIN outs o ON o.object_id = r.object_id AND o.pred = r.pred AND o.scorer = r.scorer) GROUP BY object_id)",
            f"raw{e + 1} AS MATERIALIZED (SELECT t.object_id, {cols} FROM st{e} t LEFT JOIN d{e} d ON d.object_id = t.object_id)",
        ]

    def ctes(self) -> list[str]:
        out = [*self.base(), *self.table(), self.start(), *self.state(0)]
        for e in range(self.spec.epochs):
            out += [*self.epoch(e), *self.state(e + 1)]
        truth = " AND ".join(f"({self.has(i)})" for i in range(self.k))
        out.append(f"truth AS MATERIALIZED (SELECT object_id, ({truth}) AS rel FROM chosen)")
        return out

    def rows(self, label: str) -> str:
        a, rows, spent = self.spec.alpha, [], "0.0::DOUBLE"
        for e in range(self.spec.epochs + 1):
            if e:
                spent += f" + (SELECT sum(cost) FROM plan{e - 1})"
            n = f"(SELECT count(*) FROM plan{e - 1})" if e else "0"
            rows.append(f"""SELECT '{label}' AS approach, {e} AS epoch, {spent} AS spent, CAST({n} AS BIGINT) AS items, count(*) FILTER (t.P > lam) AS answer_size, {1 + a} * max(lam) AS expected_f,
                {1 + a} * count(*) FILTER (t.P > lam AND rel) / ({a} * count(*) FILTER (rel) + count(*) FILTER (t.P > lam)) AS f1 FROM st{e} t JOIN truth USING (object_id), lam{e}""")
        return " UNION ALL ".join(rows)

    def sql(self, label: str) -> str:
        return f"SELECT * FROM (WITH {', '.join(self.ctes())} {self.rows(label)})"


def curves_sql(specs: list[tuple[str, RunSpec]]) -> str:
    return " UNION ALL ".join(SpecSql(s).sql(label) for label, s in specs)
