"""DuckDB SQL of the queries, written apart from the engine; only the generator of uniforms has the same definition."""

from __future__ import annotations

from rambler.functions import rng

T = {k: str(v << 40) for v, k in enumerate("PART SUPPLIER CUSTOMER ORDER NATION REGION SEGMENT DOCUMENT SOURCE LANG PAGE LINK TURN".split(), 1)}
_WORDS = "list_filter(regexp_split_to_array(lower(text), '[ \\n]+'), lambda w: w <> '')"

RAW = {
    "g1": "SELECT a.l_partkey AS src, b.l_partkey AS dst, a.l_quantity AS h, 0 AS label FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey",
    "g2": f"SELECT l_suppkey + {T['SUPPLIER']} AS src, l_partkey + {T['PART']} AS dst, l_quantity AS h, 0 AS label FROM lineitem UNION ALL SELECT l_partkey + {T['PART']}, l_suppkey + {T['SUPPLIER']}, l_quantity, 0 FROM lineitem",
    "g3": f"SELECT o_custkey + {T['CUSTOMER']} AS src, l_partkey + {T['PART']} AS dst, l_quantity AS h, 0 AS label FROM lineitem JOIN orders ON l_orderkey = o_orderkey UNION ALL SELECT l_partkey + {T['PART']}, o_custkey + {T['CUSTOMER']}, l_quantity, 0 FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "g4": f"""SELECT unnest([a, b]) AS src, unnest([b, a]) AS dst, h, 0 AS label FROM (
  SELECT dense_rank() OVER (ORDER BY c_mktsegment) - 1 + {T['SEGMENT']} AS a, c_custkey + {T['CUSTOMER']} AS b, greatest(c_acctbal, 0) + 1 AS h FROM customer
  UNION ALL SELECT c_nationkey::BIGINT + {T['NATION']}, c_custkey + {T['CUSTOMER']}, greatest(c_acctbal, 0) + 1 FROM customer)""",
    "g5": f"""SELECT p.id AS src, q.id AS dst, 1.0::DOUBLE AS h, 0 AS label
FROM (SELECT w[i] AS a, w[i + 1] AS b FROM (SELECT w, unnest(range(1, len(w))) AS i FROM (SELECT {_WORDS} AS w FROM documents)))
JOIN (SELECT token, row_number() OVER (ORDER BY token) - 1 AS id FROM (SELECT DISTINCT unnest({_WORDS}) AS token FROM documents)) p ON a = p.token
JOIN (SELECT token, row_number() OVER (ORDER BY token) - 1 AS id FROM (SELECT DISTINCT unnest({_WORDS}) AS token FROM documents)) q ON b = q.token""",
    "g6": "SELECT user_id AS src, nxt AS dst, value AS h, 0 AS label FROM (SELECT user_id, value, lead(user_id) OVER (ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL AND nxt <> user_id",
    "g7": f"""SELECT unnest([a, b]) AS src, unnest([b, a]) AS dst, 1.0::DOUBLE AS h, 0 AS label FROM (
  SELECT page_id + {T['PAGE']} AS a, dense_rank() OVER (ORDER BY target) - 1 + {T['LINK']} AS b FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS target FROM pages))""",
    "g8": """SELECT src, dst, greatest(c, 0) AS h, 0 AS label FROM (
  SELECT src, dst, c, row_number() OVER (PARTITION BY src ORDER BY c DESC, dst) AS r FROM (
    SELECT a.vec_id AS src, b.vec_id AS dst, list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) AS c FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id)) WHERE r <= 10""",
    "g9": "SELECT c_nationkey::BIGINT AS src, s_nationkey::BIGINT AS dst, l_extendedprice AS h, 0 AS label FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey",
    "g10": f"""SELECT n_regionkey::BIGINT + {T['REGION']} AS src, n_nationkey::BIGINT + {T['NATION']} AS dst, 1.0::DOUBLE AS h, 0 AS label FROM nation
UNION ALL SELECT c_nationkey::BIGINT + {T['NATION']}, c_custkey + {T['CUSTOMER']}, 1.0, 1 FROM customer
UNION ALL SELECT o_custkey + {T['CUSTOMER']}, o_orderkey + {T['ORDER']}, 1.0, 2 FROM orders
UNION ALL SELECT l_orderkey + {T['ORDER']}, l_partkey + {T['PART']}, l_quantity, 3 FROM lineitem
UNION ALL SELECT l_partkey + {T['PART']}, l_suppkey + {T['SUPPLIER']}, l_quantity, 4 FROM lineitem""",
    "g11": f"""SELECT doc_id + {T['DOCUMENT']} AS src, dense_rank() OVER (ORDER BY source) - 1 + {T['SOURCE']} AS dst, 1.0::DOUBLE AS h, 0 AS label FROM documents
UNION ALL SELECT doc_id + {T['DOCUMENT']}, dense_rank() OVER (ORDER BY lang) - 1 + {T['LANG']}, 1.0, 1 FROM documents""",
}


def edges(name: str, weights: str = "natural", alpha: float | None = None, seed: int = 42, labels: bool = False) -> str:
    """A subquery (src, idx, dst, h, label)."""
    base = f"SELECT src, CAST(row_number() OVER (PARTITION BY src ORDER BY dst, label) - 1 AS INTEGER) AS idx, dst, h, label FROM (SELECT src, dst, label, sum(h) AS h FROM ({RAW[name]}) GROUP BY src, dst, label)"
    u = rng.duck_uniform(seed, "src", "dst >> 32", rng.WEIGHT, "dst")
    h = {"natural": "h", "unit": "1.0::DOUBLE", "uniform": f"1 + 4 * {u}", "pareto": f"pow({u}, {-1 / (alpha or 1)!r}::DOUBLE) - 1", "degree": "h", "int8": "CAST(round(h * 127 / (max(h) OVER ())) AS DOUBLE)"}[weights]
    label = f"CAST(floor({rng.duck_uniform(seed, 'src', 'dst >> 32', rng.LABEL, 'dst')} * 5) AS INTEGER)" if labels else "label"
    if weights == "degree":
        base = f"SELECT b.src, idx, b.dst, greatest(coalesce(deg, 0), 1)::DOUBLE AS h, label FROM ({base}) b LEFT JOIN (SELECT src AS node, count(*) AS deg FROM ({base}) GROUP BY src) g ON b.dst = g.node"
    return f"SELECT src, idx, dst, {h} AS h, {label} AS label FROM ({base})"


def stats(e: str) -> str:
    return f"SELECT src, count(*) AS deg, max(h) AS h_max, min(h) AS h_min, sum(h) AS h_sum FROM ({e}) GROUP BY src"


# Weights of the models, written out once more.
WEIGHT = {
    "static": "h",
    "node2vec_w": "h * (CASE WHEN prev IS NULL THEN 1 WHEN dst = prev THEN 0.5 WHEN linked THEN 1 ELSE 2 END)::DOUBLE",
    "node2vec_u": "(CASE WHEN prev IS NULL THEN 1 WHEN dst = prev THEN 0.5 WHEN linked THEN 1 ELSE 2 END)::DOUBLE",
    "metapath_w": "CASE WHEN label = step THEN h ELSE 0 END::DOUBLE",
    "metapath_u": "(CASE WHEN label = step THEN 1 ELSE 0 END)::DOUBLE",
    "sorank_w": "h * CASE WHEN prev IS NULL THEN 1 WHEN linked AND dst <> prev THEN (0.8::DOUBLE / dc + 0.2::DOUBLE / dp) * greatest(dc, dp) ELSE 0.8::DOUBLE / dc * greatest(dc, dp) END",
    "sorank_u": "CASE WHEN prev IS NULL THEN 1::DOUBLE WHEN linked AND dst <> prev THEN (0.8::DOUBLE / dc + 0.2::DOUBLE / dp) * greatest(dc, dp) ELSE 0.8::DOUBLE / dc * greatest(dc, dp) END",
    "square": "(1 - h) * (1 - h)",
    "brand": "h * CASE WHEN dst % 5 = cur % 5 THEN 3 ELSE 1 END",
}
BOUND = {"node2vec_w": "2 * h_max", "node2vec_u": "2::DOUBLE", "static": "h_max", "square": "greatest((1 - h_max) * (1 - h_max), (1 - h_max) * (1 - h_min), (1 - h_min) * (1 - h_min))"}
TOTAL = {"node2vec_w": "(0.5 * h_sum + h_sum + 2 * h_sum) / 3", "node2vec_u": "(0.5 * deg + deg + 2 * deg) / 3", "static": "h_sum", "square": "(1 - h_sum / deg) * (1 - h_sum / deg) * deg"}


def candidates(state: str, model: str) -> str:
    """Walkers (walk_id, step, prev, cur) of `state` with all their edges of positive weight w. e, p and g: CTEs of edges, pairs and statistics."""
    return f"""SELECT walk_id, step, prev, cur, idx, dst, label, h, {WEIGHT[model]} AS w FROM (
    SELECT s.walk_id, s.step, s.prev, s.cur, e.idx, e.dst, e.label, e.h, p.src IS NOT NULL AS linked, g.deg::DOUBLE AS dc, f.deg::DOUBLE AS dp
    FROM {state} s JOIN e ON s.cur = e.src LEFT JOIN p ON s.prev = p.src AND e.dst = p.dst LEFT JOIN g ON s.cur = g.src LEFT JOIN g f ON s.prev = f.src)"""


def with_graph(name: str, **how) -> str:
    e = edges(name, **how)
    return f"e AS MATERIALIZED ({e}), p AS MATERIALIZED (SELECT DISTINCT src, dst FROM e), g AS MATERIALIZED ({stats('SELECT * FROM e')})"


def pick(state: str, model: str, sampler: str = "keys", seed: int = 42, ratio: float = 2.0) -> str:
    """(walk_id, cur, next): the step's choice for every walker of `state`."""
    c = candidates(state, model)
    key = f"-ln({rng.duck_uniform(seed, 'walk_id', 'step', rng.KEY, 'idx')}) / w"
    if sampler in ("rejection_bound", "rejection_exact") or sampler.startswith("adaptive"):
        key = f"-ln({rng.duck_uniform(seed, 'c.walk_id', 'step', rng.KEY, 'idx')}) / w"
    if sampler == "keys":
        return f"SELECT walk_id, cur, arg_min(dst, {key}) AS next FROM ({c}) WHERE w > 0 GROUP BY walk_id, cur"
    if sampler == "prefix":
        u = rng.duck_uniform(seed, "walk_id", "step", rng.KEY, "idx")
        return f"SELECT walk_id, cur, arg_max(dst, idx) AS next FROM (SELECT *, sum(w) OVER (PARTITION BY walk_id ORDER BY idx) AS acc FROM ({c}) WHERE w > 0) WHERE {u} * acc < w GROUP BY walk_id, cur"
    if sampler == "inverse":
        u = rng.duck_uniform(seed, "walk_id", "step", rng.PICK, "0")
        return f"SELECT walk_id, cur, arg_min(dst, idx) AS next FROM (SELECT *, sum(w) OVER (PARTITION BY walk_id ORDER BY idx) AS acc, sum(w) OVER (PARTITION BY walk_id) AS whole FROM ({c}) WHERE w > 0) WHERE acc > {u} * whole GROUP BY walk_id, cur"
    # Rejection, perhaps for chosen walkers only: the first of 32 trials that accepts, else keys.
    slot, height = rng.duck_uniform(seed, "walk_id", "step", rng.SLOT, "t"), rng.duck_uniform(seed, "walk_id", "step", rng.HEIGHT, "t")
    chosen = {"rejection_bound": "true", "rejection_exact": "true", "adaptive": f"{ratio} * ({BOUND[model]}) < {TOTAL[model]}", "adaptive_random": f"{rng.duck_uniform(seed, 'walk_id', 'step', rng.COIN, '0')} < 0.5",
              "adaptive_degree": "deg >= 100", "adaptive_rejection": "true", "adaptive_reservoir": "false", "adaptive_exact": f"walk_id IN (SELECT walk_id FROM ({c}) GROUP BY walk_id HAVING {ratio} * max(w) < sum(w))"}[sampler]
    bound = "top" if sampler == "rejection_exact" else BOUND[model]
    return f"""SELECT walk_id, cur, coalesce(arg_min(dst, t), arg_min(dst, k)) AS next FROM (
  SELECT c.walk_id, c.cur, c.dst, c.idx, any_value({key}) AS k, min(CASE WHEN v * ({bound}) < w THEN t END) AS t
  FROM (SELECT *, max(w) OVER (PARTITION BY walk_id) AS top FROM ({c}) WHERE w > 0) c
  LEFT JOIN (SELECT walk_id, t, h_max, h_min, h_sum, deg, least(floor({slot} * deg), deg - 1)::INTEGER AS i, {height} AS v
             FROM (SELECT walk_id, step, deg, h_max, h_min, h_sum, unnest(range(32)) AS t FROM {state} JOIN g ON cur = src) WHERE {chosen}) r
    ON c.walk_id = r.walk_id AND c.idx = r.i
  GROUP BY c.walk_id, c.cur, c.dst, c.idx) GROUP BY walk_id, cur"""


def step(name: str, model: str, sampler: str, prev: bool = True, seed: int = 42, **how) -> str:
    """One step from every node, as taken after a first step by keys (so that walkers have a previous node)."""
    first = "SELECT src AS walk_id, 0 AS step, NULL::BIGINT AS prev, src AS cur FROM g"
    return f"""WITH {with_graph(name, **how)}, s0 AS ({first}), m AS MATERIALIZED ({pick('s0', model, 'keys', seed)}),
s1 AS MATERIALIZED (SELECT walk_id, 1 AS step, cur AS prev, next AS cur FROM m) SELECT walk_id, next FROM ({pick('s1', model, sampler, seed)})"""


def walk(name: str, model: str, sampler: str = "keys", steps: int = 5, starts: str = "SELECT src AS start FROM g", seed: int = 42, **how) -> str:
    """Steps as CTEs one after another, each from the rows of the one before."""
    parts = [with_graph(name, **how), f"s0 AS MATERIALIZED (SELECT start AS walk_id, 0 AS step, NULL::BIGINT AS prev, start AS cur FROM ({starts}))"]
    for k in range(steps):
        parts.append(f"s{k + 1} AS MATERIALIZED (SELECT walk_id, {k + 1} AS step, cur AS prev, next AS cur FROM ({pick(f's{k}', model, sampler, seed)}))")
    return f"WITH {', '.join(parts)} {' UNION ALL '.join(f'SELECT walk_id, step, cur AS node FROM s{k}' for k in range(steps + 1))}"
