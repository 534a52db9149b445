"""SQL views of the workloads, written apart from the DataFrame code they check."""

BRANDS = """it AS (SELECT DISTINCT l_orderkey AS obs, p_brand AS item FROM lineitem JOIN part ON l_partkey = p_partkey),
n AS (SELECT count(*)::DOUBLE AS n FROM orders)"""

W1 = """it AS (SELECT DISTINCT l_orderkey AS obs, 'b:' || p_brand AS item FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey
UNION SELECT DISTINCT l_orderkey, 'n:' || s_nationkey FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN part ON l_partkey = p_partkey),
n AS (SELECT count(*)::DOUBLE AS n FROM orders)"""

W2 = """words AS (SELECT DISTINCT doc_id AS obs, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS item FROM documents),
top AS (SELECT item FROM words GROUP BY item ORDER BY count(*) DESC, item LIMIT 40),
it AS (SELECT obs, item FROM words WHERE item IN (SELECT item FROM top)),
n AS (SELECT count(*)::DOUBLE AS n FROM documents)"""

W3 = """line AS (SELECT row_number() OVER () AS obs, l.*, p_type, o_orderpriority, o_orderstatus, c_mktsegment, n_regionkey FROM lineitem l
LEFT JOIN part ON l_partkey = p_partkey LEFT JOIN orders ON l_orderkey = o_orderkey LEFT JOIN customer ON o_custkey = c_custkey LEFT JOIN nation ON c_nationkey = n_nationkey),
it AS (SELECT obs, item FROM (SELECT obs, unnest(['rf=' || l_returnflag, 'ls=' || l_linestatus, 'q=' || floor((l_quantity - 1) / 12.5)::INT, 'd=' || floor(l_discount * 100 / 4)::INT,
't=' || floor(l_tax * 100 / 3)::INT, 'ty=' || p_type, 'pr=' || o_orderpriority, 'st=' || o_orderstatus, 'sg=' || c_mktsegment, 'rg=' || n_regionkey]) AS item FROM line) WHERE item IS NOT NULL),
n AS (SELECT count(*)::DOUBLE AS n FROM lineitem)"""

W4 = """it AS (SELECT DISTINCT user_id || '/' || strftime(ts, '%Y-%m-%d') AS obs, event_type || '@' || (hour(ts) // 6) AS item FROM events),
n AS (SELECT count(DISTINCT user_id || '/' || strftime(ts, '%Y-%m-%d'))::DOUBLE AS n FROM events)"""

W5 = """cell AS (SELECT vec_id AS obs, unnest(embedding)::DOUBLE AS v, generate_subscripts(embedding, 1) AS i FROM embeddings),
it AS (SELECT obs, 'd' || i || CASE WHEN v > 0 THEN '+' ELSE '-' END AS item FROM cell WHERE abs(v) > 0.1),
n AS (SELECT count(*)::DOUBLE AS n FROM embeddings)"""

W6 = """it AS (SELECT DISTINCT o_custkey AS obs, p_brand AS item FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey),
n AS (SELECT count(*)::DOUBLE AS n FROM customer)"""

W7 = """it AS (SELECT DISTINCT user_id AS obs, event_type || '@' || (hour(ts) // 6) AS item FROM events),
n AS (SELECT count(DISTINCT user_id)::DOUBLE AS n FROM events)"""

VIEWS = {"w1": W1, "w2": W2, "w3": W3, "w4": W4, "w5": W5, "w6": W6, "w7": W7}


def top(k: int) -> str:
    """vars: the k most frequent items; sig: distinct rows with their number."""
    return f"""vars AS (SELECT item, row_number() OVER (ORDER BY f DESC, item) - 1 AS v FROM (SELECT item, count(*) AS f FROM it GROUP BY item ORDER BY f DESC, item LIMIT {k})),
sig AS (SELECT mask, count(*) AS w FROM (SELECT obs, sum(1::BIGINT << v::INT)::BIGINT AS mask FROM it JOIN vars USING (item) GROUP BY obs) GROUP BY mask)"""


def text(mask: str = "mask", k: int = 20) -> str:
    return f"array_to_string(list_filter(range(0, {k}), lambda i: ({mask} >> i::INT) & 1 = 1), ',')"


def frequent(k: int, min_sup: float) -> str:
    """freq: all masks above the threshold by trying each."""
    return f"""freq AS (SELECT p AS mask, sum(w)::BIGINT AS support FROM (SELECT unnest(range(1, {1 << k})) AS p) JOIN sig ON (sig.mask & p) = p GROUP BY p HAVING sum(w) / (SELECT n FROM n) > {min_sup}::DOUBLE)"""


CLOSED = "closed AS (SELECT * FROM freq a WHERE NOT EXISTS (SELECT 1 FROM freq b WHERE b.support = a.support AND b.mask <> a.mask AND (a.mask & b.mask) = a.mask))"
MAXIMAL = "closed AS (SELECT * FROM freq a WHERE NOT EXISTS (SELECT 1 FROM freq b WHERE b.mask <> a.mask AND (a.mask & b.mask) = a.mask))"


def patterns(items: str, k: int, min_sup: float, kind: str = "closed", prefix: str = "") -> str:
    """pattern, n_vars, support of the top k variables."""
    last = {"closed": ", " + CLOSED, "maximal": ", " + MAXIMAL, "all": ""}[kind]
    source = "freq" if kind == "all" else "closed"
    return f"WITH {items},\n{top(k)},\n{frequent(k, min_sup)}{last}\nSELECT {prefix}{text(k=k)} AS pattern, bit_count(mask)::INT AS n_vars, support FROM {source}"
