"""One query per generic operator that users of the mixer meet: filters, joins, aggregates, windows, sets, functions."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from mixwright.functions.hashing import uniform
from mixwright.functions.text import n_tokens
from mixwright.sources.tables import load
from mixwright.streaming import scoring

from . import oracles as sql
from .mixer import register_sql
from .queries import query


def simple(name: str, spark_sql: str, twin: str | None = None, tables: tuple[str, ...] = ()):
    """A query stated as SQL text over temporary views; the twin is the same text unless engines differ."""

    @query(name, twin or spark_sql)
    def _(spark, sf):
        for t in tables:
            load(spark, sf, t).createOrReplaceTempView(t)
        return spark.sql(spark_sql)


# projections, filters, predicates
simple("q_project_tokens", "SELECT doc_id, n_chars, n_chars * 2 AS doubled, upper(lang) AS lang_upper, concat(source, '/', lang) AS place FROM documents", tables=("documents",))
simple("q_filter_range", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND NOT l_tax > 0.04", tables=("lineitem",))
simple("q_filter_regex", "SELECT doc_id FROM documents WHERE regexp_like(text, '[0-9]{3}') OR text LIKE 'The%' OR startswith(text, 'La')", "SELECT doc_id FROM documents WHERE regexp_matches(text, '[0-9]{3}') OR text LIKE 'The%' OR starts_with(text, 'La')", ("documents",))
simple("q_case_quality_band", "SELECT doc_id, CASE WHEN quality = 1 AND toxic = 0 THEN 'good' WHEN quality = 1 THEN 'toxic' ELSE 'poor' END AS band, coalesce(nullif(quality, 0), -1) AS q, greatest(quality, toxic) AS hi, least(quality, toxic) AS lo FROM labels", tables=("labels",))
simple("q_null_safe", "SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE NOT l.quality <=> 1", "SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality IS DISTINCT FROM 1", ("documents", "labels"))
simple("q_casts", "SELECT event_id, CAST(value AS BIGINT) AS whole, try_cast(event_type AS INT) AS no_number, CAST(user_id AS STRING) AS user_text FROM events WHERE value = floor(value) OR event_id >= 0 AND CAST(value AS BIGINT) = floor(value)", "SELECT event_id, floor(value)::BIGINT AS whole, TRY_CAST(event_type AS INT) AS no_number, user_id::VARCHAR AS user_text FROM events", ("events",))
simple("q_array_predicates", "SELECT vec_id, size(filter(embedding, x -> x > 0)) AS n_positive, exists(embedding, x -> x > 0.3) AS any_large, forall(embedding, x -> abs(x) < 0.5) AS all_small FROM embeddings", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0))::INT AS n_positive, len(list_filter(embedding, lambda x: x > 0.3::DOUBLE)) > 0 AS any_large, len(list_filter(embedding, lambda x: abs(x) >= 0.5::DOUBLE)) = 0 AS all_small FROM embeddings", ("embeddings",))


@query("q_hash_sample", f"SELECT doc_id, lang FROM documents WHERE {sql.draw(seed=5)} < CASE lang WHEN 'en' THEN 0.1 WHEN 'fr' THEN 0.5 ELSE 1.0 END")
def _(spark, sf):
    rate = F.when(F.col("lang") == "en", 0.1).when(F.col("lang") == "fr", 0.5).otherwise(1.0)
    return load(spark, sf, "documents").select("doc_id", "lang").filter(uniform("doc_id", 5) < rate)


# joins
J = ("lineitem", "part", "supplier", "orders", "customer", "nation", "region", "documents", "labels", "embeddings", "events")
simple("q_join_broadcast", "SELECT /*+ BROADCAST(n) */ c_custkey, n_name FROM customer JOIN nation n ON c_nationkey = n_nationkey", "SELECT c_custkey, n_name FROM customer JOIN nation n ON c_nationkey = n_nationkey", J)
simple("q_join_merge", "SELECT /*+ MERGE(l) */ o_orderkey, count(*) AS n FROM orders JOIN lineitem l ON o_orderkey = l_orderkey GROUP BY o_orderkey", "SELECT o_orderkey, count(*) AS n FROM orders JOIN lineitem l ON o_orderkey = l_orderkey GROUP BY o_orderkey", J)
simple("q_join_hash", "SELECT /*+ SHUFFLE_HASH(l) */ d.doc_id, l.quality FROM documents d JOIN labels l ON d.doc_id = l.doc_id", "SELECT d.doc_id, l.quality FROM documents d JOIN labels l ON d.doc_id = l.doc_id", J)
simple("q_join_outer", "SELECT coalesce(l.doc_id, e.vec_id) AS doc_id, l.quality, e.label FROM labels l FULL OUTER JOIN embeddings e ON l.doc_id = e.vec_id", tables=J)
simple("q_join_left", "SELECT d.doc_id, l.quality IS NULL AS missing FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id", tables=J)
simple("q_join_semi", "SELECT doc_id FROM documents d LEFT SEMI JOIN labels l ON d.doc_id = l.doc_id AND l.toxic = 1", "SELECT doc_id FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE d.doc_id = l.doc_id AND l.toxic = 1)", J)
simple("q_join_anti", "SELECT doc_id FROM documents d LEFT ANTI JOIN labels l ON d.doc_id = l.doc_id", "SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE d.doc_id = l.doc_id)", J)
simple("q_join_small_tables", "SELECT r_name, n_name FROM region CROSS JOIN nation WHERE n_regionkey <> r_regionkey", tables=J)
simple("q_join_range", "SELECT band, count(*) AS n FROM documents JOIN (VALUES ('short', 0, 500), ('mid', 500, 2000), ('long', 2000, 10000000)) b(band, low, high) ON n_chars >= low AND n_chars < high GROUP BY band", tables=J)
simple("q_join_star", "SELECT p_brand, s_nationkey, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey WHERE o_orderpriority LIKE '1%' GROUP BY p_brand, s_nationkey", tables=J)
simple("q_join_lateral", "SELECT doc_id, alpha, quality * alpha AS part FROM labels, LATERAL (SELECT explode(array(0.0D, 0.5D, 1.0D)) AS alpha)", "SELECT doc_id, alpha, quality * alpha AS part FROM labels, (SELECT unnest([0.0, 0.5, 1.0]::DOUBLE[]) AS alpha)", J)
simple("q_join_self", "SELECT a.label, count(*) AS n FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id = b.vec_id - 1 GROUP BY a.label", tables=J)

# aggregates
simple("q_agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS total, round(avg(l_discount), 6) AS mean, min(l_tax) AS low, max(l_tax) AS high, round(stddev(l_quantity), 6) AS sd, round(var_pop(l_quantity), 6) AS var FROM lineitem GROUP BY l_returnflag, l_linestatus", tables=J)
simple("q_agg_filtered", "SELECT lang, count(*) FILTER (WHERE n_chars < 1000) AS n_short, count(*) AS n, bool_or(n_chars > 20000) AS any_long, bool_and(n_chars > 0) AS none_empty FROM documents GROUP BY lang", tables=J)
simple("q_agg_distinct", "SELECT count(DISTINCT source) AS sources, count(DISTINCT lang) AS langs, count(DISTINCT source, lang) AS pairs FROM documents", "SELECT count(DISTINCT source) AS sources, count(DISTINCT lang) AS langs, count(DISTINCT (source, lang)) AS pairs FROM documents", J)
simple("q_agg_quantiles", "SELECT lang, percentile(n_chars, 0.5) AS p50, percentile(n_chars, 0.9) AS p90 FROM documents GROUP BY lang", "SELECT lang, quantile_cont(n_chars, 0.5)::DOUBLE AS p50, quantile_cont(n_chars, 0.9)::DOUBLE AS p90 FROM documents GROUP BY lang", J)
simple("q_agg_histogram", "SELECT width_bucket(l_quantity, 0, 50, 10) AS bucket, count(*) AS n FROM lineitem GROUP BY 1", "SELECT (CASE WHEN l_quantity >= 50 THEN 11 ELSE floor(l_quantity / 5) + 1 END)::BIGINT AS bucket, count(*) AS n FROM lineitem GROUP BY 1", J)
simple("q_agg_rollup", "SELECT r_name, n_name, count(*) AS n, round(sum(c_acctbal), 2) AS balance, grouping(n_name)::INT AS level FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)", "SELECT r_name, n_name, count(*) AS n, round(sum(c_acctbal), 2) AS balance, grouping(n_name)::INT AS level FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)", J)
simple("q_agg_cube", "SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)", tables=J)
simple("q_agg_grouping_sets", "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())", tables=J)
simple("q_agg_corr", "SELECT round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_pop(l_quantity, l_extendedprice), 4) AS cov, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope FROM lineitem", tables=J)
simple("q_agg_lists", "SELECT source, array_join(array_sort(collect_set(lang)), ',') AS langs, max_by(doc_id, struct(n_chars, doc_id)) AS longest, min_by(doc_id, struct(n_chars, doc_id)) AS shortest FROM documents GROUP BY source", "SELECT source, string_agg(DISTINCT lang, ',' ORDER BY lang) AS langs, arg_max(doc_id, (n_chars, doc_id)) AS longest, arg_min(doc_id, (n_chars, doc_id)) AS shortest FROM documents GROUP BY source", J)
simple("q_agg_entropy", "SELECT round(-sum(s * ln(s)), 6) AS entropy, round(1 / sum(s * s), 6) AS effective FROM (SELECT count(*) / sum(count(*)) OVER () AS s FROM documents GROUP BY lang)", tables=J)
simple("q_agg_logsumexp", "SELECT source, round(m + ln(sum(exp(x - m))), 6) AS lse FROM (SELECT source, n_chars / 1000 AS x, max(n_chars / 1000) OVER (PARTITION BY source) AS m FROM documents) GROUP BY source, m", tables=J)
simple("q_pivot", "SELECT * FROM (SELECT source, lang FROM documents) PIVOT (count(*) FOR lang IN ('en' AS en, 'fr' AS fr, 'de' AS de, 'es' AS es))", "SELECT source, nullif(count(*) FILTER (lang = 'en'), 0) AS en, nullif(count(*) FILTER (lang = 'fr'), 0) AS fr, nullif(count(*) FILTER (lang = 'de'), 0) AS de, nullif(count(*) FILTER (lang = 'es'), 0) AS es FROM documents GROUP BY source", J)
simple("q_unpivot", "SELECT doc_id, kind, mark FROM labels UNPIVOT (mark FOR kind IN (quality, toxic))", "SELECT doc_id, 'quality' AS kind, quality::INT AS mark FROM labels UNION ALL SELECT doc_id, 'toxic', toxic::INT FROM labels", J)


@query("q_agg_approx")
def _(spark, sf):
    """Sketches beside exact figures."""
    d = load(spark, sf, "documents")
    return d.agg(F.approx_count_distinct("text").alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("text")).alias("hll"), F.count_distinct("text").alias("exact"), F.percentile_approx("n_chars", 0.5).alias("approx_median"), F.percentile("n_chars", F.lit(0.5)).alias("median"))


@query("q_agg_skew_salted", "SELECT lang, count(*) AS n, sum(n_chars)::BIGINT AS total FROM documents GROUP BY lang")
def _(spark, sf):
    """Two-level aggregate over salted keys."""
    salted = load(spark, sf, "documents").select("lang", "n_chars", F.pmod(F.xxhash64("doc_id"), F.lit(16)).alias("salt"))
    part = salted.groupBy("lang", "salt").agg(F.count("*").alias("n"), F.sum("n_chars").alias("total"))
    return part.groupBy("lang").agg(F.sum("n").cast("long").alias("n"), F.sum("total").cast("long").alias("total"))


@query("q_agg_theta_kll", "SELECT lang, count(DISTINCT source || '/' || n_chars) AS exact, true AS theta_within, true AS kll_within FROM documents GROUP BY lang")
def _(spark, sf):
    """Theta and KLL sketches by group: the number of distinct pairs within 5 %, and the median between the exact 45th and 55th percentiles."""
    d = load(spark, sf, "documents").select("lang", F.concat_ws("/", "source", "n_chars").alias("pair"), "n_chars")
    own = d.groupBy("lang").agg(F.count_distinct("pair").alias("exact"), F.theta_sketch_estimate(F.theta_sketch_agg("pair")).alias("theta"), F.kll_sketch_agg_bigint("n_chars").alias("kll"), F.percentile("n_chars", F.array(F.lit(0.45), F.lit(0.55))).alias("around"))
    middle = F.kll_sketch_get_quantile_bigint("kll", F.lit(0.5))
    return own.select("lang", "exact", (F.abs(F.col("theta") - F.col("exact")) <= 0.05 * F.col("exact") + 1).alias("theta_within"), middle.between(F.col("around")[0] - 1, F.col("around")[1] + 1).alias("kll_within"))


@query("q_join_skew_salted", "SELECT l_returnflag, p_brand, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY ALL")
def _(spark, sf):
    """A join whose keys are spread: the large side takes a salt by hash, the small one is repeated for every salt; no side is broadcast."""
    salts = 8
    line = load(spark, sf, "lineitem").select("l_partkey", "l_returnflag", "l_quantity", F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(salts)).cast("int").alias("salt"))
    part = load(spark, sf, "part").select("p_partkey", "p_brand", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("part_salt"))
    both = line.hint("merge").join(part.hint("merge"), (F.col("l_partkey") == F.col("p_partkey")) & (F.col("salt") == F.col("part_salt")))
    return both.groupBy("l_returnflag", "p_brand").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query("q_cogroup_map", "SELECT coalesce(d.source, l.source) AS source, coalesce(n_docs, 0) AS n_docs, coalesce(n_good, 0) AS n_good FROM (SELECT source, count(*) AS n_docs FROM documents GROUP BY 1) d FULL JOIN (SELECT source, count(*) AS n_good FROM documents JOIN labels USING (doc_id) WHERE quality = 1 GROUP BY 1) l USING (source)")
def _(spark, sf):
    """Two tables met group by group in Arrow."""
    import pyarrow as pa

    docs = load(spark, sf, "documents").select("doc_id", "source")
    good = docs.join(load(spark, sf, "labels").filter("quality = 1"), "doc_id").select(F.col("source").alias("from_source"), F.col("doc_id").alias("good_id"))

    def sizes(key: tuple, a: pa.Table, b: pa.Table) -> pa.Table:
        return pa.table({"source": [key[0].as_py()], "n_docs": [a.num_rows], "n_good": [b.num_rows]})

    return docs.groupBy("source").cogroup(good.groupBy("from_source")).applyInArrow(sizes, "source string, n_docs long, n_good long")


@query("q_sort_ranges", "SELECT doc_id, n_chars, lag(doc_id) OVER (PARTITION BY floor(n_chars / 1000) ORDER BY n_chars, doc_id) AS before FROM documents")
def _(spark, sf):
    """Range partitions sorted apart; a neighbour is read off within bands."""
    d = load(spark, sf, "documents").select("doc_id", "n_chars").withColumn("band", F.floor(F.col("n_chars") / 1000))
    ranged = d.repartitionByRange(8, "band").sortWithinPartitions("band", "n_chars", "doc_id")
    return ranged.withColumn("before", F.lag("doc_id").over(Window.partitionBy("band").orderBy("n_chars", "doc_id"))).drop("band")


# windows
W = "WINDOW w AS (PARTITION BY lang ORDER BY n_chars, doc_id)"
simple("q_window_ranks", f"SELECT doc_id, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, ntile(4) OVER w AS quarter FROM documents {W}", f"SELECT doc_id, (row_number() OVER w)::INT AS rn, (rank() OVER w)::INT AS rk, (dense_rank() OVER w)::INT AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, (ntile(4) OVER w)::INT AS quarter FROM documents {W}", J)
simple("q_window_offsets", f"SELECT doc_id, lag(n_chars) OVER w AS before, lead(n_chars, 2) OVER w AS after, first_value(doc_id) OVER w AS first_doc, nth_value(doc_id, 3) OVER w AS third FROM documents {W}", tables=J)
simple("q_window_running", "SELECT doc_id, sum(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS UNBOUNDED PRECEDING) AS upto, round(n_chars / sum(n_chars) OVER (PARTITION BY source), 6) AS share FROM documents", "SELECT doc_id, (sum(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS UNBOUNDED PRECEDING))::BIGINT AS upto, round(n_chars / sum(n_chars) OVER (PARTITION BY source), 6) AS share FROM documents", J)
simple("q_window_sliding", "SELECT event_id, round(avg(value) OVER (PARTITION BY event_type ORDER BY event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS smooth FROM events", tables=J)
simple("q_window_peers", "SELECT doc_id, count(*) OVER (PARTITION BY lang ORDER BY quality RANGE UNBOUNDED PRECEDING) AS by_range, count(*) OVER (PARTITION BY lang ORDER BY quality, doc_id ROWS UNBOUNDED PRECEDING) AS by_rows FROM documents JOIN labels USING (doc_id)", tables=J)
simple("q_window_zscore", "SELECT doc_id, round((n_chars - avg(n_chars) OVER (PARTITION BY lang)) / stddev_pop(n_chars) OVER (PARTITION BY lang), 6) AS z FROM documents", tables=J)
simple("q_top_per_group", "SELECT source, doc_id, n_chars FROM (SELECT *, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS k FROM documents) WHERE k <= 3", tables=J)

# sorts and sets
simple("q_top_k", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20", tables=J)
simple("q_offset", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars, doc_id LIMIT 10 OFFSET 5", tables=J)
simple("q_union_all", "SELECT doc_id FROM labels UNION ALL SELECT vec_id FROM embeddings", tables=J)
simple("q_union", "SELECT doc_id FROM labels UNION SELECT vec_id FROM embeddings", tables=J)
simple("q_intersect", "SELECT doc_id FROM labels INTERSECT SELECT vec_id FROM embeddings", tables=J)
simple("q_intersect_all", "SELECT lang FROM documents INTERSECT ALL SELECT lang FROM documents JOIN labels USING (doc_id)", tables=J)
simple("q_except", "SELECT vec_id FROM embeddings EXCEPT SELECT doc_id FROM labels", tables=J)
simple("q_except_all", "SELECT lang FROM documents EXCEPT ALL SELECT lang FROM documents JOIN labels USING (doc_id)", tables=J)
simple("q_distinct", "SELECT DISTINCT lang, source FROM documents", tables=J)

# functions
simple("q_strings", "SELECT doc_id, lower(left(text, 20)) AS low, length(text) AS chars, substring(text, 3, 5) AS part, regexp_replace(left(text, 30), '[aeiou]', '_') AS masked, instr(text, 'e') AS at, reverse(lang) AS backwards, lpad(source, 8, '.') AS padded, repeat(lang, 2) AS twice, levenshtein(lang, source) AS edits FROM documents", "SELECT doc_id, lower(left(text, 20)) AS low, length(text)::INT AS chars, substring(text, 3, 5) AS part, regexp_replace(left(text, 30), '[aeiou]', '_', 'g') AS masked, instr(text, 'e')::INT AS at, reverse(lang) AS backwards, lpad(source, 8, '.') AS padded, repeat(lang, 2) AS twice, levenshtein(lang, source)::INT AS edits FROM documents", J)
simple("q_hashes", "SELECT doc_id, md5(text) AS m, sha2(text, 256) AS s FROM documents", "SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM documents", J)
simple("q_math", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(exp(l_discount), 6) AS e, round(ln(l_quantity), 6) AS l, round(sqrt(l_extendedprice), 6) AS r, floor(l_extendedprice / 7) AS f, ceil(l_tax * 10) AS c, abs(l_discount - 0.05) AS a, sign(l_discount - 0.05) AS sgn FROM lineitem", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(exp(l_discount), 6) AS e, round(ln(l_quantity), 6) AS l, round(sqrt(l_extendedprice), 6) AS r, floor(l_extendedprice / 7)::BIGINT AS f, ceil(l_tax * 10)::BIGINT AS c, abs(l_discount - 0.05::DOUBLE) AS a, sign(l_discount - 0.05::DOUBLE)::DOUBLE AS sgn FROM lineitem", J)
simple("q_arrays", "SELECT vec_id, round(aggregate(embedding, 0D, (a, x) -> a + x), 5) AS total, round(array_max(embedding), 6) AS top, size(slice(embedding, 3, 4)) AS four, round(element_at(embedding, -1), 6) AS last FROM embeddings", "SELECT vec_id, round(list_sum(embedding::DOUBLE[]), 5) AS total, round(list_max(embedding), 6) AS top, 4 AS four, round(embedding[-1], 6) AS last FROM embeddings", J)
simple("q_json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS INT) AS k, from_json(props, 'k INT').k AS k2 FROM events", "SELECT event_id, json_extract_string(props, '$.k')::INT AS k, json_extract_string(props, '$.k')::INT AS k2 FROM events", J)
simple("q_variant", "SELECT event_id, variant_get(parse_json(props), '$.k', 'int') AS k FROM events", "SELECT event_id, json_extract_string(props, '$.k')::INT AS k FROM events", J)
simple("q_dates", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, hour(o_orderdate) AS h, datediff(o_orderdate, DATE'1992-01-01') AS days FROM orders", "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, hour(o_orderdate)::INT AS h, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS days FROM orders", J)
simple("q_maps", "SELECT source, map_from_entries(array_sort(collect_list(struct(lang, n))))['en'] AS en FROM (SELECT source, lang, count(*) AS n FROM documents GROUP BY source, lang) GROUP BY source", "SELECT source, nullif(count(*) FILTER (lang = 'en'), 0) AS en FROM documents GROUP BY source", J)


@query("q_sql_functions", f"{sql.mixer_cte()} SELECT doc_id, round(p, 6) AS p, copies FROM drawn")
def _(spark, sf):
    """The method from SQL text: registered functions, scalar subqueries for the normalisers."""
    from .queries import scored
    from mixwright.operators import sampling

    register_sql(spark)
    sampling.minmax(scored(spark, sf)).createOrReplaceTempView("scaled_documents")
    spark.sql("SELECT doc_id, mix_weight(diversity_01, quality_01, :alpha) AS p FROM scaled_documents", args={"alpha": 0.8}).createOrReplaceTempView("weighed_documents")
    spark.sql("SELECT doc_id, p, exp((p - (SELECT max(p) FROM weighed_documents)) / :tau) AS e FROM weighed_documents", args={"tau": 0.2}).createOrReplaceTempView("sharpened_documents")
    return spark.sql(
        "SELECT doc_id, round(p, 6) AS p, mix_copies((SELECT count(*) FROM sharpened_documents) * :share * e / (SELECT sum(e) FROM sharpened_documents), mix_draw(doc_id, 42)) AS copies FROM sharpened_documents",
        args={"share": 1.0},
    )


@query("q_udtf_ngrams", f"SELECT item_id, unnest(range(0, len(w) - 1))::INT AS position, unnest(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS gram FROM (SELECT item_id, {sql.words()} AS w FROM benchmark)")
def _(spark, sf):
    from mixwright.functions.udfs import NGrams

    spark.udtf.register("word_ngrams", NGrams)
    load(spark, sf, "benchmark").createOrReplaceTempView("benchmark")
    return spark.sql("SELECT item_id, g.position, g.gram FROM benchmark, LATERAL word_ngrams(text, 2) g")


@query("q_udaf_logsumexp", "SELECT source, round(m + ln(sum(exp(x - m))), 6) AS lse FROM (SELECT source, n_chars / 1000 AS x, max(n_chars / 1000) OVER (PARTITION BY source) AS m FROM documents) GROUP BY source, m")
def _(spark, sf):
    from mixwright.functions.udfs import log_sum_exp

    return load(spark, sf, "documents").groupBy("source").agg(F.round(log_sum_exp(F.col("n_chars") / 1000), 6).alias("lse"))


# streams' batch twins and as-of joins
@query("events_tumbling", "SELECT epoch(time_bucket(INTERVAL 1 HOUR, ts))::BIGINT AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def _(spark, sf):
    t = scoring.tumbling(scoring.event_time(load(spark, sf, "events")))
    return t.select(F.unix_seconds("start").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


@query("events_sliding", "SELECT epoch(b)::BIGINT AS start, event_type, count(*) AS n, round(avg(value), 6) AS mean FROM (SELECT unnest([time_bucket(INTERVAL 1 HOUR, ts), time_bucket(INTERVAL 1 HOUR, ts) - INTERVAL 1 HOUR]) AS b, event_type, value FROM events) GROUP BY ALL")
def _(spark, sf):
    t = scoring.sliding(scoring.event_time(load(spark, sf, "events")))
    return t.select(F.unix_seconds("start").alias("start"), "event_type", "n", F.round("mean", 6).alias("mean"))


@query("events_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 10 MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, epoch_us(min(ts)) AS start, count(*) AS n FROM s GROUP BY user_id, k")
def _(spark, sf):
    return scoring.sessions(scoring.event_time(load(spark, sf, "events"))).select("user_id", F.unix_micros("start").alias("start"), "n")


@query("asof_params", "WITH p AS (SELECT min(ts) + (max(ts) - min(ts)) * k / 5 AS since, k AS version FROM events, (SELECT unnest([0, 1, 2, 3, 4]) AS k) GROUP BY k), e AS (SELECT event_id, ts FROM events) SELECT version::INT AS version, count(*) AS n FROM e ASOF JOIN (SELECT * FROM p) p ON e.ts >= p.since GROUP BY version")
def _(spark, sf):
    """Each event takes the parameter version valid at its time: a union in time order, and the last version carried on inside hourly
    partitions, with versions repeated at each partition's start so that no global window is needed."""
    e = load(spark, sf, "events").select("event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    ends = e.agg(F.min("us").alias("low"), F.max("us").alias("high"))
    versions = spark.range(5).select(F.col("id").cast("int").alias("version")).crossJoin(F.broadcast(ends)).select("version", (F.col("low") + F.floor((F.col("high") - F.col("low")) * F.col("version") / 5)).alias("since"))
    spans = versions.withColumn("till", F.lead("since").over(Window.orderBy("version")))  # five rows
    hit = e.join(F.broadcast(spans), (F.col("us") >= F.col("since")) & (F.col("till").isNull() | (F.col("us") < F.col("till"))))
    return hit.groupBy("version").agg(F.count("*").alias("n"))


@query("narrow_scan", f"SELECT source, count(*) AS n, sum(len({sql.words()}))::BIGINT AS n_tokens FROM documents GROUP BY source")
def _(spark, sf):
    return load(spark, sf, "documents").groupBy("source").agg(F.count("*").alias("n"), F.sum(n_tokens("text")).cast("long").alias("n_tokens"))
