"""DuckDB SQL that recomputes families, searches, baselines and traces; projections enter as values."""

from __future__ import annotations

from dataclasses import dataclass

from objann.functions.params import WIDTHS, collision_prob
from objann.operators.hashing import Projections
from objann.sources.families import PARTS, TURNS, Family

EMBEDDED = "list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * 65536 + 0.5) AS BIGINT))"
TWIN_POINTS = f"""e AS (SELECT vec_id, {EMBEDDED} AS v FROM embeddings), n AS (SELECT count(*) AS n FROM embeddings), pts AS (
  SELECT CAST(t.id // 12 AS BIGINT) AS object_id, CAST(t.id AS BIGINT) AS point_id,
         list_transform(range(1, 65), lambda i: 20 * a.v[i] + 3 * b.v[i] + 7 * c.v[i]) AS vec
  FROM n, range(CAST((SELECT count(*) // 5 * 12 FROM embeddings) AS BIGINT)) t(id) JOIN e a ON a.vec_id = (t.id // 12) // 2 JOIN e b ON b.vec_id = n * 4 // 5 + (t.id // 12) % 2
  JOIN e c ON c.vec_id = (12 * (t.id // 12) + 7 * (t.id % 12) + 100) % n
)"""


def q16(value: str) -> str:
    return f"CAST(floor(CAST({value} AS DOUBLE) * 65536 + 0.5) AS BIGINT)"


def line_points(key: str) -> str:
    source = "lineitem" if key != "o_custkey" else "(SELECT l.*, o_custkey FROM lineitem l JOIN orders ON l_orderkey = o_orderkey)"
    vec = ", ".join(q16(v) for v in ("l_quantity / 50.0::DOUBLE", "l_extendedprice / 105000.0::DOUBLE", "l_discount * 10.0::DOUBLE", "l_tax * 12.5::DOUBLE", "CAST(date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE)) AS DOUBLE) / 2500.0::DOUBLE"))
    order = "l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate"
    return f"pts AS (SELECT {key} AS object_id, {key} * 1048576 + row_number() OVER (PARTITION BY {key} ORDER BY {order}) AS point_id, [{vec}] AS vec FROM {source})"


def user_points() -> str:
    kinds = ", ".join(q16(f"CASE WHEN event_type = '{k}' THEN 1.0 ELSE 0.0 END") for k in ("view", "click", "signup", "error", "purchase"))
    k = "CAST(json_extract_string(props, '$.k') AS DOUBLE) / 100.0::DOUBLE"
    return f"pts AS (SELECT user_id AS object_id, event_id AS point_id, [{q16('sqrt(1.0::DOUBLE + value) / 22.0::DOUBLE')}, {q16('CAST(hour(ts) AS DOUBLE) / 24.0::DOUBLE')}, {kinds}, {q16(k)}] AS vec FROM events)"


def text_points(table: str, key: str, text: str) -> str:
    """Sentences and lines as signed 3-gram counts; ``key`` is an expression."""
    return f"""pieces AS (SELECT {key} AS object_id, string_split_regex({text}, '[.\\n]') AS p FROM {table} WHERE {text} IS NOT NULL
), parts AS (SELECT object_id, unnest(range(len(p))) AS place, unnest(p) AS part FROM pieces
), codes AS (SELECT object_id, place, list_transform(string_split(trim(part, ' '), ''), lambda c: CAST(unicode(c) AS BIGINT)) AS c FROM parts WHERE length(trim(part, ' ')) >= 20
), grams AS (SELECT object_id, place, list_transform(range(1, len(c) - 1), lambda i: (c[i] * 961 + c[i + 1] * 31 + c[i + 2]) % 1000003) AS h FROM codes
), bins AS (SELECT object_id, place, list_transform(range(32), lambda b: CAST(coalesce(list_sum(list_transform(list_filter(h, lambda x: x % 32 = b), lambda x: 1 - 2 * (x // 32 % 2))), 0) AS DOUBLE)) AS b FROM grams
), pts AS (SELECT CAST(object_id AS BIGINT) AS object_id, CAST(object_id * {PARTS} + place AS BIGINT) AS point_id,
  list_transform(b, lambda x: CAST(floor(x / sqrt(list_sum(list_transform(b, lambda y: y * y))) * 65536 + 0.5) AS BIGINT)) AS vec FROM bins WHERE list_sum(list_transform(b, lambda y: y * y)) > 0)"""


def family_points(name: str) -> str:
    """CTEs up to ``pts`` (object_id, point_id, vec) of a family."""
    lines = {"supp": "l_suppkey", "part": "l_partkey", "order": "l_orderkey", "cust": "o_custkey"}
    if name in lines:
        return line_points(lines[name])
    if name == "conv":
        slots = text_points("conversations", f"conv_id * {TURNS} + turn", "text")
        return f"{slots.replace('pts AS', 'slots AS')}, pts AS (SELECT object_id // {TURNS} AS object_id, point_id, vec FROM slots)"
    return {
        "twin": lambda: TWIN_POINTS,
        "emb": lambda: f"pts AS (SELECT CAST(vec_id // 20 AS BIGINT) AS object_id, vec_id AS point_id, {EMBEDDED} AS vec FROM embeddings)",
        "label": lambda: f"pts AS (SELECT CAST(label AS BIGINT) AS object_id, vec_id AS point_id, {EMBEDDED} AS vec FROM embeddings)",
        "user": user_points,
        "doc": lambda: text_points("documents", "doc_id", "text"),
        "bench": lambda: text_points("benchmark", "item_id", "text"),
        "page": lambda: text_points("pages", "page_id", "regexp_replace(html, '<[^>]*>', chr(10), 'g')"),
    }[name]()


def parameters(delta: float = 0.1, c: float = 2) -> str:
    """Projections and thresholds for beta = 25 over the number of objects, from the collision probabilities as values."""
    columns = []
    for kind, w in WIDTHS.items():
        p1, p2 = (f"{collision_prob(kind, s, w)!r}::DOUBLE" for s in (1, c))
        m = f"ceil(ln(1 / {delta}::DOUBLE) * (1 + z) ** 2 / (2 * ({p1} - {p2}) ** 2))"
        columns.append(f"CAST({m} AS INTEGER) AS {kind}_m, CAST(ceil((z * {p1} + {p2}) / (1 + z) * {m}) AS INTEGER) AS {kind}_l")
    counts = " UNION ALL ".join(f"SELECT '{name}' AS family, count(DISTINCT {key}) AS n FROM {table}" for name, table, key in (("supp", "lineitem", "l_suppkey"), ("part", "lineitem", "l_partkey"), ("order", "lineitem", "l_orderkey"), ("user", "events", "user_id")))
    beta = "CASE WHEN n <= 25 THEN 0.999::DOUBLE ELSE 25.0::DOUBLE / n END"
    return f"WITH c AS ({counts}), r AS (SELECT family, n, sqrt(ln(2 / ({beta})) / ln(1 / {delta}::DOUBLE)) AS z FROM c) SELECT family, CAST(n AS INTEGER) AS n_objects, {', '.join(columns)} FROM r"


def shown(name: str) -> str:
    return f"WITH {family_points(name)} SELECT object_id, point_id, array_to_string(vec, ',') AS vec FROM pts"


def floor_div(v: str, w) -> str:
    return f"(({v}) - ((({v}) % ({w})) + ({w})) % ({w})) // ({w})"


@dataclass(frozen=True)
class Sql:
    """The texts for one family and a query set, given as a condition on object_id.  ``from_points`` may name other query points."""

    family: Family
    queries: str
    queried: str | None = None  # CTEs of another family's points as ``qpts``

    @property
    def points(self) -> str:
        return family_points(self.family.name) + (f", {self.queried}" if self.queried else "")

    @property
    def pairs(self) -> str:
        source = "qpts" if self.queried else "pts"
        return f"""{self.points}, sz AS (SELECT object_id, count(*) AS nx FROM pts GROUP BY 1
), qp AS (SELECT object_id AS q_obj, point_id AS q_id, vec AS qv FROM {source} WHERE {self.queries}
), qz AS (SELECT q_obj, count(*) AS nq FROM qp GROUP BY 1
), pairs AS (
  SELECT q_obj, q_id, object_id, point_id, CAST(list_sum(list_transform(range(1, {self.family.dim + 1}), lambda i: (qv[i] - vec[i]) * (qv[i] - vec[i]))) AS BIGINT) AS sq_dist FROM qp, pts
)"""

    def distances(self, n: int, d: int) -> str:
        return f"""{self.pairs}, numbered AS (
  SELECT q_obj, object_id, sq_dist, row_number() OVER (PARTITION BY q_obj, object_id ORDER BY sq_dist) AS rn,
         greatest(1, (count(*) OVER (PARTITION BY q_obj, object_id) * {n} + {d - 1}) // {d}) AS rank_in_pairs FROM pairs
), gd AS (SELECT q_obj, object_id, rank_in_pairs, sq_dist FROM numbered WHERE rn = rank_in_pairs)"""

    def truth(self, n: int, d: int, k: int) -> str:
        return f"""{self.distances(n, d)}, truth AS (
  SELECT q_obj, CAST(row_number() OVER (PARTITION BY q_obj ORDER BY sq_dist, object_id) AS INTEGER) AS rank, object_id, sq_dist FROM gd QUALIFY rank <= {k}
)"""

    def linear(self, k: int) -> str:
        return f"""{self.pairs}, knn AS (
  SELECT q_obj, q_id, CAST(row_number() OVER (PARTITION BY q_obj, q_id ORDER BY sq_dist, object_id, point_id) AS INTEGER) AS rank, object_id, point_id, sq_dist FROM pairs QUALIFY rank <= {k}
)"""

    def hashes(self, p: Projections) -> str:
        rows = ", ".join(f"({j + 1}, {a.tolist()}::BIGINT[], {int(b)}::BIGINT)" for j, (a, b) in enumerate(zip(p.a, p.b)))
        dot = f"CAST(list_sum(list_transform(range(1, {self.family.dim + 1}), lambda i: vec[i] * a[i])) AS BIGINT)"
        h = floor_div(f"{dot} + b", p.width) if p.static else dot
        return f"pj(proj, a, b) AS (VALUES {rows}), h AS (SELECT object_id, point_id, proj, CAST({h} AS BIGINT) AS bucket FROM pts, pj)"

    @staticmethod
    def first_level(p: Projections, top: int | None = None) -> str:
        out = "NULL"
        for t in range(p.levels if top is None else top, -1, -1):
            r = p.limits()[t]
            same = f"{floor_div('q.bucket', r)} = {floor_div('x.bucket', r)}" if p.static else f"2 * abs(q.bucket - x.bucket) <= {r}"
            out = f"CASE WHEN {same} THEN {t} ELSE {out} END"
        return out

    def reach(self, p: Projections, step: float, column: str = "sq_dist") -> str:
        out = str(p.levels + 1)
        for t in range(p.levels, -1, -1):
            out = f"CASE WHEN {column} <= {p.squared_radii(self.family.unit, step)[t]} THEN {t} ELSE {out} END"
        return out

    def firsts(self, p: Projections) -> str:
        return f"""{self.hashes(p)}, firsts AS (
  SELECT q.object_id AS q_obj, q.point_id AS q_id, x.object_id, x.point_id, q.proj, {self.first_level(p)} AS t FROM h q JOIN h x ON q.proj = x.proj WHERE q.{self.queries}
), close AS (SELECT q_obj, q_id, object_id, point_id, key FROM (
  SELECT q_obj, q_id, object_id, point_id, t * {p.params.m + 1} + proj AS key, row_number() OVER (PARTITION BY q_id, point_id ORDER BY t * {p.params.m + 1} + proj) AS pos FROM firsts WHERE t IS NOT NULL) WHERE pos = {p.params.l})"""

    def search(self, p: Projections, n: int, d: int, k: int, eps=(1, 5), mode: str = "carry", step: float = 1, exclude_self: bool = False) -> str:
        """CTEs up to ``stops``, ``inside`` and ``found`` of the whole search as order statistics; more than 25 objects."""
        m = p.params.m
        num, den = (eps[1] - eps[0]) * n, eps[1] * d
        last = p.levels * (m + 1) + m
        if mode == "carry":
            events = "events AS (SELECT q_obj, object_id, -1 AS turn, key FROM close)"
        else:
            events = f"""events AS (SELECT q_obj, object_id, turn, turn * {m + 1} + proj AS key FROM (
          SELECT q_obj, object_id, l.turn, proj, row_number() OVER (PARTITION BY q_id, point_id, l.turn ORDER BY proj) AS pos FROM firsts, range({p.levels + 1}) l(turn) WHERE t <= l.turn) WHERE pos = {p.params.l})"""
        return f"""{self.distances(n, d)}, {self.firsts(p)}, {events}, upto AS (
  SELECT q_obj, object_id, key, row_number() OVER (PARTITION BY q_obj, object_id, turn ORDER BY key) AS n FROM events
), keys AS (SELECT q_obj, object_id, min(key) AS key FROM upto JOIN sz USING (object_id) JOIN qz USING (q_obj) WHERE n * {den} >= nx * nq * {num} {"AND q_obj <> object_id" if exclude_self else ""} GROUP BY 1, 2
), t1 AS (SELECT q_obj, key AS t1 FROM (SELECT *, row_number() OVER (PARTITION BY q_obj ORDER BY key, object_id) AS pos FROM keys) WHERE pos = {k + 25}
), near AS (SELECT q_obj, object_id, greatest(key // {m + 1}, {self.reach(p, step)}) AS level FROM keys JOIN gd USING (q_obj, object_id)
), t2 AS (SELECT q_obj, level * {m + 1} + {m} AS t2 FROM (SELECT *, row_number() OVER (PARTITION BY q_obj ORDER BY level, object_id) AS pos FROM near) WHERE pos = {k} AND level <= {p.levels}
), stops AS (
  SELECT q_obj, CASE WHEN t1 IS NULL AND t2 IS NULL THEN 'exhausted' WHEN coalesce(t1, {last + 1}) <= coalesce(t2, {last + 1}) THEN 'T1' ELSE 'T2' END AS status,
         least(coalesce(t1, {last}), coalesce(t2, {last})) AS stop
  FROM (SELECT DISTINCT q_obj FROM qp) LEFT JOIN t1 USING (q_obj) LEFT JOIN t2 USING (q_obj)
), inside AS (SELECT q_obj, object_id, sq_dist, key FROM keys JOIN stops USING (q_obj) JOIN gd USING (q_obj, object_id) WHERE key <= stop
), found AS (SELECT q_obj, CAST(row_number() OVER (PARTITION BY q_obj ORDER BY sq_dist, object_id) AS INTEGER) AS rank, object_id, sq_dist FROM inside QUALIFY rank <= {k})"""

    @staticmethod
    def stats(p: Projections) -> str:
        m = p.params.m
        return f"SELECT q_obj, status, CAST(stop // {m + 1} AS INTEGER) AS stop_level, CAST(stop % {m + 1} AS INTEGER) AS stop_proj, coalesce(n, 0) AS n_candidates FROM stops LEFT JOIN (SELECT q_obj, count(*) AS n FROM inside GROUP BY 1) USING (q_obj)"

    def hashed_knn(self, p: Projections, k: int) -> str:
        """CTEs up to ``knn`` of the point search with a stop for each query point."""
        m = p.params.m
        last = p.levels * (m + 1) + m
        return f"""{self.pairs}, {self.firsts(p)}, met AS (SELECT c.*, sq_dist FROM close c JOIN pairs USING (q_obj, q_id, object_id, point_id)
), t1 AS (SELECT q_id, key AS t1 FROM (SELECT *, row_number() OVER (PARTITION BY q_id ORDER BY key, point_id) AS pos FROM met) WHERE pos = {k + 100}
), t2 AS (SELECT q_id, level * {m + 1} + {m} AS t2 FROM (SELECT q_id, level, row_number() OVER (PARTITION BY q_id ORDER BY level, point_id) AS pos FROM (SELECT q_id, point_id, greatest(key // {m + 1}, {self.reach(p, p.params.c)}) AS level FROM met)) WHERE pos = {k} AND level <= {p.levels}
), knn AS (SELECT q_obj, q_id, CAST(row_number() OVER (PARTITION BY q_obj, q_id ORDER BY sq_dist, point_id, object_id) AS INTEGER) AS rank, object_id, point_id, sq_dist
  FROM met LEFT JOIN t1 USING (q_id) LEFT JOIN t2 USING (q_id) WHERE key <= least(coalesce(t1, {last}), coalesce(t2, {last})) QUALIFY rank <= {k})"""

    @staticmethod
    def borda(ctes: str, score: str, k: int) -> str:
        return f"WITH {ctes}, sc AS ({score}) SELECT q_obj, CAST(row_number() OVER (PARTITION BY q_obj ORDER BY score DESC, object_id) AS INTEGER) AS rank, object_id, score FROM sc QUALIFY rank <= {k}"

    @staticmethod
    def positional(k: int) -> str:
        return f"SELECT q_obj, object_id, CAST(sum({k + 1} - rank) AS DOUBLE) AS score FROM knn GROUP BY 1, 2"

    RATIO = """SELECT q_obj, round(avg(CASE WHEN t.sq_dist = 0 AND f.sq_dist = 0 THEN 1.0 WHEN t.sq_dist = 0 THEN NULL ELSE sqrt(CAST(f.sq_dist AS DOUBLE)) / sqrt(CAST(t.sq_dist AS DOUBLE)) END), 6) AS object_ratio,
  round(count(f.sq_dist) / count(*), 6) AS coverage, CAST(sum(CASE WHEN t.sq_dist = 0 AND f.sq_dist > 0 THEN 1 ELSE 0 END) AS BIGINT) AS n_undefined
  FROM truth t LEFT JOIN found f USING (q_obj, rank) GROUP BY 1"""
    RECALL = "SELECT q_obj, round(count(f.object_id) / count(*), 6) AS recall FROM truth t LEFT JOIN found f USING (q_obj, object_id) GROUP BY 1"

    def with_truth(self, p: Projections, n: int, d: int, k: int) -> str:
        found = self.search(p, n, d, k)
        return f"WITH {found}, truth AS (SELECT q_obj, CAST(row_number() OVER (PARTITION BY q_obj ORDER BY sq_dist, object_id) AS INTEGER) AS rank, object_id, sq_dist FROM gd QUALIFY rank <= {k})"

    def trace(self, p: Projections, n_splits: int = 1, top: int | None = None) -> str:
        """CTEs up to ``trace``: accesses in joint order."""
        slices = f"least({n_splits}, length)"
        return f"""{self.points}, {self.hashes(p)}, cat AS (SELECT proj, bucket, count(*) * 8 AS bytes FROM h GROUP BY 1, 2
), need AS (SELECT * FROM (
  SELECT q.object_id AS q_obj, q.point_id AS q_id, q.proj, {self.first_level(p, top)} AS level, q.bucket AS own, x.bucket, x.bytes FROM h q JOIN cat x ON q.proj = x.proj WHERE q.{self.queries}) WHERE level IS NOT NULL
), ranged AS (SELECT *, CAST(1 AS BIGINT) << level AS length FROM need
), lowered AS (SELECT *, length * ({floor_div('own', 'length')}) AS low FROM ranged
), cut AS (SELECT *, CAST((bucket - low) // CAST(ceil(length / {slices}) AS BIGINT) AS INTEGER) AS split_id, CAST(ceil(length / {slices}) AS BIGINT) AS size FROM lowered
), trace AS (SELECT q_obj, row_number() OVER (PARTITION BY q_obj ORDER BY level, proj, low + split_id * size, q_id, bucket) AS seq, CAST(level AS INTEGER) AS level, proj, q_id, bucket, bytes, split_id, low + split_id * size AS start FROM cut)"""

    LRU = """), last AS (SELECT q_obj, seq, proj, bucket, lag(seq) OVER (PARTITION BY q_obj, proj, bucket ORDER BY seq) AS last FROM trace
), dist AS (SELECT x.q_obj, x.seq, x.last, count(y.seq) AS d FROM last x LEFT JOIN last y ON x.q_obj = y.q_obj AND y.seq > x.last AND y.seq < x.seq AND coalesce(y.last, 0) <= x.last GROUP BY 1, 2, 3
) SELECT q_obj, CAST(sum(CASE WHEN last IS NOT NULL AND d < PAGES THEN 1 ELSE 0 END) AS BIGINT) AS hits, CAST(sum(CASE WHEN last IS NOT NULL AND d < PAGES THEN 0 ELSE 1 END) AS BIGINT) AS misses FROM dist GROUP BY 1"""

    def lru(self, p: Projections, pages: int, top: int) -> str:
        return f"WITH {self.trace(p, 1, top)[:-1]}{self.LRU}".replace("PAGES", str(pages))
