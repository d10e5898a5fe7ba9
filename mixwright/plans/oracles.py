"""SQL twins of the registered queries, in DuckDB's dialect, from shared common table expressions."""

from __future__ import annotations

ORACLES: dict[str, str] = {}

TOKENS = r"CASE WHEN trim(coalesce({0}, '')) = '' THEN []::VARCHAR[] ELSE regexp_split_to_array(trim({0}), '\s+') END"


def words(col: str = "text") -> str:
    return TOKENS.format(col)


def draw(expr: str = "doc_id::VARCHAR", seed: int = 42) -> str:
    return f"(('0x' || substr(md5('{seed}:' || {expr}), 1, 13))::BIGINT / 4503599627370496.0::DOUBLE)"


def bucket(expr: str, n: int) -> str:
    return f"(('0x' || substr(md5({expr}), 1, 8))::BIGINT % {n})"


def distance(metric: str, a: str = "x", b: str = "g") -> str:
    if metric == "cosine":
        return f"1 - sum({a} * {b}) / sqrt(sum({a} * {a}) * sum({b} * {b}))"
    return f"sqrt(sum(({a} - {b}) * ({a} - {b})))" if metric == "euclidean" else f"sum(({a} - {b}) * ({a} - {b}))"


def clusters_cte(metric: str = "euclidean", sep: str = "avg(gap)") -> str:
    return f"""
    dims AS (SELECT vec_id, label AS cluster, unnest(embedding::DOUBLE[]) AS x, generate_subscripts(embedding, 1) AS i FROM embeddings),
    cent AS (SELECT cluster, i, avg(x) AS g FROM dims GROUP BY ALL),
    gone AS (SELECT vec_id, cluster, {distance(metric)} AS dist FROM dims JOIN cent USING (cluster, i) GROUP BY vec_id, cluster),
    compact AS (SELECT cluster, count(*) AS n, avg(dist) AS compactness FROM gone GROUP BY cluster),
    gaps AS (SELECT a.cluster, b.cluster AS other, {distance(metric, 'a.g', 'b.g')} AS gap FROM cent a JOIN cent b ON a.i = b.i AND a.cluster <> b.cluster GROUP BY 1, 2),
    sep AS (SELECT cluster, {sep} AS separation FROM gaps GROUP BY cluster),
    clus AS (SELECT cluster, n, compactness, separation, compactness * separation AS diversity FROM compact JOIN sep USING (cluster))"""


def scored_cte(sep: str = "avg(gap)") -> str:
    return clusters_cte(sep=sep) + f""",
    scored AS (SELECT d.doc_id, d.source, d.lang AS domain, len({words('d.text')})::BIGINT AS n_tokens, l.quality::INT AS quality, e.label AS cluster, c.diversity, md5(d.text) AS text_hash
      FROM documents d JOIN labels l USING (doc_id) JOIN embeddings e ON e.vec_id = d.doc_id JOIN clus c ON c.cluster = e.label)"""


def line_cte() -> str:
    """lineitem rows as documents: discount levels as quality, brands as clusters over (quantity, price, tax) vectors."""
    return f"""
    line AS (SELECT concat_ws('/', l_orderkey, l_linenumber, l_partkey, l_suppkey, round(l_extendedprice * 100)::BIGINT) AS doc_id, l_returnflag || '|' || l_linestatus AS domain, l_quantity::BIGINT AS n_tokens,
      round(l_discount * 100)::INT AS quality, p_brand AS cluster, [l_quantity / 50, l_extendedprice / 100000, l_tax * 10]::DOUBLE[] AS v FROM lineitem JOIN part ON l_partkey = p_partkey),
    lv AS (SELECT cluster, v[1] AS a, v[2] AS b, v[3] AS c FROM line),
    lc AS (SELECT cluster, avg(a) AS ga, avg(b) AS gb, avg(c) AS gc FROM lv GROUP BY cluster),
    lk AS (SELECT cluster, avg(sqrt((a - ga) * (a - ga) + (b - gb) * (b - gb) + (c - gc) * (c - gc))) AS compactness FROM lv JOIN lc USING (cluster) GROUP BY cluster),
    ls AS (SELECT x.cluster, avg(sqrt((x.ga - y.ga) * (x.ga - y.ga) + (x.gb - y.gb) * (x.gb - y.gb) + (x.gc - y.gc) * (x.gc - y.gc))) AS separation FROM lc x JOIN lc y ON x.cluster <> y.cluster GROUP BY x.cluster),
    scored AS (SELECT line.doc_id, line.domain, line.n_tokens, line.quality, line.cluster, round(compactness * separation, 12) AS diversity FROM line JOIN lk USING (cluster) JOIN ls USING (cluster))"""


def scaled_cte(of: str = "scored") -> str:
    part = lambda c: f"CASE WHEN h{c} > l{c} THEN ({c} - l{c}) / (h{c} - l{c}) ELSE 0.0 END AS {c}_01"
    return f"""
    ends AS (SELECT min(quality)::DOUBLE AS lquality, max(quality)::DOUBLE AS hquality, min(diversity) AS ldiversity, max(diversity) AS hdiversity FROM {of}),
    scaled AS (SELECT s.*, {part('quality')}, {part('diversity')} FROM {of} s, ends)"""


def freq_cte(alpha: float = 0.8, tau: float = 0.2, share: float = 1.0, budget: str = "documents", of: str = "scored") -> str:
    scale = "n_total * goal / t_total / z_total" if budget == "documents" else "goal / zt_total"
    return (
        scaled_cte(of)
        + f""",
    weighed AS (SELECT *, {alpha}::DOUBLE * diversity_01 + {1.0 - alpha}::DOUBLE * quality_01 AS p FROM scaled),
    top AS (SELECT max(p) AS p_top FROM weighed),
    sums AS (SELECT sum(exp((p - p_top) / {tau})) AS z_total, count(*)::DOUBLE AS n_total, sum(n_tokens)::DOUBLE AS t_total, sum(exp((p - p_top) / {tau}) * n_tokens) AS zt_total, {share}::DOUBLE * sum(n_tokens) AS goal FROM weighed, top),
    freq AS (SELECT w.*, {scale} * exp((p - p_top) / {tau}) AS c FROM weighed w, top, sums)"""
    )


def drawn_cte(seed: int = 42) -> str:
    return f"""
    drawn AS (SELECT *, (floor(round(c, 9)) + CASE WHEN {draw(seed=seed)} < round(c, 9) - floor(round(c, 9)) THEN 1 ELSE 0 END)::INT AS copies FROM freq)"""


def mixer_cte(alpha: float = 0.8, tau: float = 0.2, share: float = 1.0, budget: str = "documents", base: str | None = None) -> str:
    return "WITH " + (base or scored_cte()) + "," + freq_cte(alpha, tau, share, budget) + "," + drawn_cte()
