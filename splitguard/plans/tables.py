"""Queries on the operators around the methods: joins, aggregates, windows, sets, scalars, streams."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from splitguard import oracles as O
from splitguard.functions.dct import PAPER_OPS
from splitguard.functions.register import leakage_report, register
from splitguard.operators import collide
from splitguard.operators import fingerprint as fp
from splitguard.operators.raster import split_of
from splitguard.plans.asof import as_of_join, interval_join
from splitguard.plans.audits import _part, hashes, versions
from splitguard.sources.carriers import table
from splitguard.streaming import guard

_SPLIT = O.split_case("doc_id")


def _docs(spark, sf_dir):
    return table(spark, sf_dir, "documents").withColumn("split", split_of(F.col("doc_id")))


def scan_pruned_documents(spark, sf_dir):
    """Only two columns are read, and the filter reaches the scan."""
    return table(spark, sf_dir, "documents").where("n_chars > 2000 AND lang = 'en'").select("doc_id", "n_chars")


def filter_docs_lang_size(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    kept = docs.where(
        F.col("lang").isin("en", "fr") & F.col("n_chars").between(500, 1500) & F.col("source").like("src1%")
        & ~F.col("text").rlike(r"[0-9]")
    )
    return kept.select("doc_id", "lang", "n_chars", F.coalesce("source", F.lit("none")).alias("source"))


def nullsafe_hash_match(spark, sf_dir):
    h = hashes(spark, sf_dir, "part").withColumn("hash", F.when(F.pmod("image_id", F.lit(10)) != 0, F.col("hash")))
    index = _part(h, "train").select(F.col("hash").alias("known")).distinct()
    val = _part(h, "val")
    return val.join(index, val["hash"].eqNullSafe(index["known"]), "left_semi").select("image_id")


def join_semi_val_train(spark, sf_dir):
    h = hashes(spark, sf_dir, "documents")
    return _part(h, "val").join(_part(h, "train").select("hash").distinct(), "hash", "left_semi").select("image_id")


def join_anti_train_val(spark, sf_dir):
    h = hashes(spark, sf_dir, "documents")
    return _part(h, "train").join(_part(h, "val").select("hash").distinct(), "hash", "left_anti").select("image_id")


def join_broadcast_nation(spark, sf_dir):
    nation = table(spark, sf_dir, "nation")  # 25 rows by definition
    customers = table(spark, sf_dir, "customer").select("c_nationkey", "c_acctbal")
    joined = customers.join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.groupBy("n_name").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


def _hinted(how):
    def run(spark, sf_dir):
        parts = table(spark, sf_dir, "part").select("p_partkey", "p_brand")
        lines = table(spark, sf_dir, "lineitem").select("l_partkey")
        joined = lines.join(parts.hint(how), F.col("l_partkey") == F.col("p_partkey"))
        return joined.groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"))

    return run


def join_theta_hamming(spark, sf_dir):
    """The stated queries, every id divisible by 20, against all other pages."""
    h = hashes(spark, sf_dir, "pages")
    near = collide.hamming_search(h.where("image_id % 20 = 0"), h, 16)
    return near.where("a <> b")


def join_asof_events_orders(spark, sf_dir):
    """Each order with the last event of the same day count of its customer's remainder, at or before it."""
    events = table(spark, sf_dir, "events").select(
        F.col("user_id").alias("k"), F.col("ts").alias("event_ts"), F.col("event_id")
    )
    orders = table(spark, sf_dir, "orders").select(
        F.pmod("o_custkey", F.lit(10)).alias("k"), F.col("o_orderkey"),
        (F.timestamp_seconds(F.lit(1704067200)).cast("timestamp_ntz")
         + F.make_dt_interval(F.pmod("o_orderkey", F.lit(30)), F.pmod("o_custkey", F.lit(24)))).alias("order_ts"),
    )
    last = as_of_join(orders, events, "k", "order_ts", "event_ts", ["event_id"])
    return last.select("o_orderkey", "event_id")


def join_interval_events(spark, sf_dir):
    """Pairs of a purchase and another event of the user within the hour after it."""
    events = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "ts")
    left = events.where("event_type = 'purchase'").select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"))
    right = events.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"))
    return interval_join(left, right, "user_id", "ta", "tb", 3600).where("a <> b").select("a", "b")


def join_outer_coverage(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang")
    labels = table(spark, sf_dir, "labels").select("doc_id", "quality")
    both = docs.join(labels, "doc_id", "full")
    return both.groupBy("lang").agg(
        F.count(F.lit(1)).alias("n"), F.count("quality").alias("n_labelled"), F.coalesce(F.sum("quality"), F.lit(0)).alias("n_good")
    )


def agg_docs_by_lang_split(spark, sf_dir):
    return _docs(spark, sf_dir).groupBy("lang", "split").agg(
        F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"), F.count_distinct("source").alias("sources"),
        F.max_by("doc_id", F.struct("n_chars", "doc_id")).alias("longest"), F.count_if(F.col("n_chars") > 2000).alias("n_long"),
        F.bit_or("n_chars").alias("any_bits"), F.bit_xor("n_chars").alias("odd_bits"), F.percentile("n_chars", F.lit(0.5)).alias("median_chars"),
    )


def rollup_lang_source(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return docs.rollup("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("level"))


def cube_lang_split(spark, sf_dir):
    return _docs(spark, sf_dir).cube("lang", "split").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("level"))


def grouping_sets_quality(spark, sf_dir):
    docs = _docs(spark, sf_dir).select("doc_id", "lang", "split")
    joined = docs.join(table(spark, sf_dir, "labels"), "doc_id")
    return joined.groupingSets([["lang", "quality"], ["split"], []], "lang", "quality", "split").agg(F.count(F.lit(1)).alias("n"))


def approx_distinct_hashes(spark, sf_dir):
    h = hashes(spark, sf_dir, "part")
    return h.agg(
        F.approx_count_distinct("hash", 0.02).alias("approx"),
        F.hll_sketch_estimate(F.hll_sketch_agg("hash")).alias("sketch"),
        F.length(F.count_min_sketch("hash", F.lit(0.01), F.lit(0.95), F.lit(7))).alias("sketch_bytes"),
        F.count_distinct("hash").alias("exact"),
    )


def pivot_split_counts(spark, sf_dir):
    return _docs(spark, sf_dir).groupBy("lang").pivot("split", ["train", "val", "test"]).agg(F.count(F.lit(1)))


def window_keep_first(spark, sf_dir):
    nth = F.row_number().over(Window.partitionBy("hash").orderBy("image_id"))
    return hashes(spark, sf_dir, "part").withColumn("nth", nth).where("nth = 1").select("image_id", "hash")


def window_running_dup_rate(spark, sf_dir):
    """Share of copies among the part images so far, in blocks of one hundred ids."""
    nth = F.row_number().over(Window.partitionBy("hash").orderBy("image_id"))
    marked = hashes(spark, sf_dir, "part").select("image_id", (nth > 1).cast("long").alias("copy"))
    blocks = marked.groupBy(F.expr("image_id div 100").alias("block")).agg(F.sum("copy").alias("copies"), F.count(F.lit(1)).alias("n"))
    upto = Window.orderBy("block").rowsBetween(Window.unboundedPreceding, 0)  # one row a block
    return blocks.select("block", F.sum("copies").over(upto).alias("copies"), F.sum("n").over(upto).alias("n"))


def window_lag_gap_events(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    gap = F.unix_timestamp(F.col("ts").cast("timestamp")) - F.unix_timestamp(F.lag("ts").over(w).cast("timestamp"))
    return table(spark, sf_dir, "events").select(
        "event_id", gap.alias("gap_s"), F.lead("event_id").over(w).alias("following"),
        F.ntile(4).over(w).alias("quarter"), F.dense_rank().over(Window.partitionBy("user_id").orderBy("event_type")).alias("kind"),
        F.first("event_id").over(w).alias("first_event"),
    )


def window_range_7d_orders(spark, sf_dir):
    day = F.datediff(F.col("o_orderdate"), F.lit("1970-01-01").cast("date"))
    w = Window.partitionBy("o_custkey").orderBy("day").rangeBetween(-6, 0)
    orders = table(spark, sf_dir, "orders").withColumn("day", day)
    return orders.select("o_orderkey", F.count(F.lit(1)).over(w).alias("n_week"), F.round(F.sum("o_totalprice").over(w), 2).alias("spent"))


def topk_largest_groups(spark, sf_dir):
    groups = hashes(spark, sf_dir, "part").groupBy("hash").agg(F.count(F.lit(1)).alias("n"))
    return groups.orderBy(F.desc("n"), "hash").limit(10)


def topk_per_split(spark, sf_dir):
    w = Window.partitionBy("split").orderBy(F.desc("n_chars"), "doc_id")
    return _docs(spark, sf_dir).select("split", "doc_id", F.rank().over(w).alias("nth")).where("nth <= 5")


def setop_intersect_hashes(spark, sf_dir):
    h = hashes(spark, sf_dir, "part")
    return _part(h, "train").select("hash").intersect(_part(h, "test").select("hash"))


def setop_except_hashes(spark, sf_dir):
    h = hashes(spark, sf_dir, "part")
    return _part(h, "test").select("hash").exceptAll(_part(h, "train").select("hash"))


def setop_union_collections(spark, sf_dir):
    both = hashes(spark, sf_dir, "pages").select("hash").unionByName(hashes(spark, sf_dir, "benchmark").select("hash"))
    return both.groupBy("hash").agg(F.count(F.lit(1)).alias("n"))


def string_hash_format(spark, sf_dir):
    h = F.col("hash")
    return hashes(spark, sf_dir, "pages").select(
        "image_id", F.substring(fp.hash_hex(h), 1, 4).alias("head"), F.substring(fp.hash_bits(h), 61, 4).alias("tail"),
        F.octet_length(fp.hash_bits(h)).alias("bytes"), F.levenshtein(F.substring(fp.hash_hex(h), 1, 4), F.substring(fp.hash_hex(h), 5, 4)).alias("edits"),
    )


def string_normalized_duplicates(spark, sf_dir):
    norm = F.regexp_replace(F.lower("text"), "[^a-z]+", " ")
    docs = table(spark, sf_dir, "documents").select("doc_id", F.md5(F.trim(norm)).alias("digest"))
    return docs.groupBy("digest").agg(F.min("doc_id").alias("group_id"), F.count(F.lit(1)).alias("n")).where("n > 1")


def date_activity_cells(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(
        F.dayofmonth("ts").alias("day"), F.hour("ts").alias("hour"), F.date_trunc("month", "ts").cast("date").alias("month")
    ).agg(F.count(F.lit(1)).alias("n"), F.max(F.datediff("ts", F.lit("2024-01-01").cast("date"))).alias("days"))


def bitwise_hamming_profile(spark, sf_dir):
    """Distances of every page hash to the least page's hash."""
    h = hashes(spark, sf_dir, "pages")
    first = h.agg(F.min_by("hash", "image_id").alias("h0"))
    far = fp.hamming(F.col("hash"), F.col("h0"))
    return h.join(F.broadcast(first), how="left").groupBy(far.cast("int").alias("distance")).agg(F.count(F.lit(1)).alias("n"))


def array_orientation_overlap(spark, sf_dir):
    """Images some of whose orientations look alike, from the arrays alone."""
    v = versions(spark, sf_dir, "part", PAPER_OPS)
    return v.select(
        "image_id", F.size(F.array_distinct("hashes")).alias("n_distinct"), F.array_min("hashes").alias("least"),
        F.arrays_overlap(F.slice("hashes", 1, 1), F.slice("hashes", 2, 5)).alias("symmetric"),
    )


def map_group_sizes(spark, sf_dir):
    """Sizes of the splits inside each duplicate group, as a map of the splits that have any."""
    h = hashes(spark, sf_dir, "part")
    counts = h.groupBy("hash").agg(*[F.count_if(F.col("split") == s).alias(s) for s in ("train", "val", "test")])
    pairs = F.array(*[F.struct(F.lit(s).alias("k"), F.col(s).alias("v")) for s in ("train", "val", "test")])
    present = F.map_filter(F.map_from_entries(pairs), lambda k, v: v > 0)
    return counts.select("hash", F.array_join(F.array_sort(F.map_keys(present)), "+").alias("splits"), F.size(present).alias("n_splits"))


def json_event_props(spark, sf_dir):
    k = F.from_json("props", "k int")["k"]
    other = F.try_variant_get(F.parse_json("props"), "$.k", "int")
    events = table(spark, sf_dir, "events")
    return events.groupBy("event_type").agg(
        F.sum(k).alias("k"), F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k_path"), F.sum(other).alias("k_variant")
    )


# ---- streams ---------------------------------------------------------------------------


def _plain_start(df):
    return df.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


def stream_tumbling_events(spark, sf_dir):
    return _plain_start(guard.run_to_table(guard.tumbling_counts(guard.event_stream(spark, sf_dir)), "complete"))


def stream_sliding_events(spark, sf_dir):
    return _plain_start(guard.run_to_table(guard.sliding_counts(guard.event_stream(spark, sf_dir)), "complete"))


def stream_session_events(spark, sf_dir):
    return _plain_start(guard.run_to_table(guard.session_counts(guard.event_stream(spark, sf_dir)), "complete"))


def stream_dedup_events(spark, sf_dir):
    firsts = guard.first_arrivals(guard.event_stream(spark, sf_dir), "props")
    return guard.run_to_table(firsts.select("props"))


def stream_leak_guard(spark, sf_dir):
    """Documents arriving as a stream, fingerprinted and judged against the index of the train split."""
    index = collide.hash_index(_part(hashes(spark, sf_dir, "documents"), "train"))
    arrivals = guard.text_stream(spark, sf_dir, "documents", "doc_id", "text").where("split <> 'train'")
    return guard.run_to_table(guard.raster_guard(arrivals, index, "text"))


def stream_first_seen_state(spark, sf_dir):
    seen = guard.run_to_table(guard.first_seen_state(guard.event_stream(spark, sf_dir), "user_id"), "update")
    latest = seen.groupBy("key").agg(F.max("n").alias("n"), F.min("first_ts").alias("first_ts"))
    return latest.select("key", "n", F.date_format("first_ts", "yyyy-MM-dd HH").alias("first_hour"))


# ---- functions for SQL --------------------------------------------------------------


def udf_phash_sql(spark, sf_dir):
    register(spark)
    table(spark, sf_dir, "pages").createOrReplaceTempView("v_udf_pages")
    return spark.sql("SELECT page_id AS image_id, phash_udf(html) AS hash, ahash_udf(html) AS average, "
        "hamming(phash_udf(html), ahash_udf(html)) AS apart FROM v_udf_pages"
    )


def udtf_orientations(spark, sf_dir):
    register(spark)
    versions(spark, sf_dir, "pages").createOrReplaceTempView("v_udtf_pages")
    return spark.sql("SELECT image_id, o.op, o.hash FROM v_udtf_pages, LATERAL orientations(hashes) AS o")


def udaf_bit_balance(spark, sf_dir):
    register(spark)
    hashes(spark, sf_dir, "pages").createOrReplaceTempView("v_udaf_pages")
    return spark.sql("SELECT split, round(bit_balance(hash), 6) AS mean_bits FROM v_udaf_pages GROUP BY split")


def sql_leakage_report(spark, sf_dir):
    return leakage_report(spark, sf_dir)


def entries():
    part, doc, page = O.hashed("part"), O.hashed("documents"), O.hashed("pages")
    docs = f"(SELECT *, {_SPLIT} AS split FROM documents)"
    hexed = "lpad(lower(printf('%x', CASE WHEN hash < 0 THEN hash::HUGEINT + 18446744073709551616 ELSE hash::HUGEINT END)), 16, '0')"
    brand = "SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1"
    start = "strftime({0}, '%Y-%m-%d %H:%M:%S') AS start"
    return {
        "scan_pruned_documents": (scan_pruned_documents, "SELECT doc_id, n_chars FROM documents WHERE n_chars > 2000 AND lang = 'en'"),
        "filter_docs_lang_size": (filter_docs_lang_size, """SELECT doc_id, lang, n_chars, coalesce(source, 'none') AS source FROM documents
WHERE lang IN ('en', 'fr') AND n_chars BETWEEN 500 AND 1500 AND source LIKE 'src1%' AND NOT regexp_matches(text, '[0-9]')"""),
        "nullsafe_hash_match": (nullsafe_hash_match, O.with_(f"{part}, h AS (SELECT image_id, split, CASE WHEN image_id % 10 <> 0 THEN hash END AS hash FROM v)",
            "SELECT image_id FROM h WHERE split = 'val' AND EXISTS (SELECT 1 FROM h AS t WHERE t.split = 'train' AND t.hash IS NOT DISTINCT FROM h.hash)")),
        "join_semi_val_train": (join_semi_val_train, O.with_(doc, "SELECT image_id FROM v WHERE split = 'val' AND hash IN (SELECT hash FROM v WHERE split = 'train')")),
        "join_anti_train_val": (join_anti_train_val, O.with_(doc, "SELECT image_id FROM v WHERE split = 'train' AND hash NOT IN (SELECT hash FROM v WHERE split = 'val')")),
        "join_broadcast_nation": (join_broadcast_nation, "SELECT n_name, count(*) AS n, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1"),
        "join_hint_hash": (_hinted("shuffle_hash"), brand),
        "join_hint_merge": (_hinted("merge"), brand),
        "join_theta_hamming": (join_theta_hamming, O.with_(page, """SELECT x.image_id AS a, y.image_id AS b, bit_count(xor(x.hash, y.hash))::INTEGER AS distance
FROM v AS x JOIN v AS y ON x.image_id % 20 = 0 AND x.image_id <> y.image_id AND bit_count(xor(x.hash, y.hash)) <= 16""")),
        "join_asof_events_orders": (join_asof_events_orders, """WITH o AS (SELECT o_orderkey, o_custkey % 10 AS k,
    TIMESTAMP '2024-01-01' + to_days((o_orderkey % 30)::INTEGER) + to_hours(o_custkey % 24) AS order_ts FROM orders)
SELECT o_orderkey, (SELECT arg_max(event_id, (ts, event_id)) FROM events WHERE user_id = k AND ts <= order_ts) AS event_id FROM o"""),
        "join_interval_events": (join_interval_events, """SELECT x.event_id AS a, y.event_id AS b FROM events AS x JOIN events AS y
ON x.user_id = y.user_id AND x.event_type = 'purchase' AND y.ts >= x.ts AND y.ts <= x.ts + INTERVAL 3600 SECOND AND x.event_id <> y.event_id"""),
        "join_outer_coverage": (join_outer_coverage, """SELECT lang, count(*) AS n, count(quality) AS n_labelled, coalesce(sum(quality), 0)::BIGINT AS n_good
FROM documents FULL JOIN labels USING (doc_id) GROUP BY lang"""),
        "agg_docs_by_lang_split": (agg_docs_by_lang_split, f"""SELECT lang, split, count(*) AS n, sum(n_chars)::BIGINT AS chars, count(DISTINCT source) AS sources,
    arg_max(doc_id, (n_chars, doc_id)) AS longest, count(*) FILTER (n_chars > 2000) AS n_long, bit_or(n_chars) AS any_bits,
    bit_xor(n_chars) AS odd_bits, quantile_cont(n_chars::DOUBLE, 0.5) AS median_chars FROM {docs} GROUP BY ALL"""),
        "rollup_lang_source": (rollup_lang_source, "SELECT lang, source, count(*) AS n, grouping(lang, source)::BIGINT AS level FROM documents GROUP BY ROLLUP (lang, source)"),
        "cube_lang_split": (cube_lang_split, f"SELECT lang, split, count(*) AS n, grouping(lang, split)::BIGINT AS level FROM {docs} GROUP BY CUBE (lang, split)"),
        "grouping_sets_quality": (grouping_sets_quality, f"SELECT lang, quality, split, count(*) AS n FROM {docs} JOIN labels USING (doc_id) GROUP BY GROUPING SETS ((lang, quality), (split), ())"),
        "approx_distinct_hashes": (approx_distinct_hashes, None),
        "pivot_split_counts": (pivot_split_counts, f"SELECT lang, nullif(count(*) FILTER (split = 'train'), 0) AS train, nullif(count(*) FILTER (split = 'val'), 0) AS val, nullif(count(*) FILTER (split = 'test'), 0) AS test FROM {docs} GROUP BY lang"),
        "window_keep_first": (window_keep_first, O.with_(part, "SELECT min(image_id) AS image_id, hash FROM v GROUP BY hash")),
        "window_running_dup_rate": (window_running_dup_rate, O.with_(part, """SELECT block, sum(c) OVER (ORDER BY block)::BIGINT AS copies, sum(n) OVER (ORDER BY block)::BIGINT AS n FROM (
    SELECT image_id // 100 AS block, sum(copy) AS c, count(*) AS n FROM (
        SELECT image_id, (row_number() OVER (PARTITION BY hash ORDER BY image_id) > 1)::INT AS copy FROM v) GROUP BY 1)""")),
        "window_lag_gap_events": (window_lag_gap_events, """SELECT event_id, (floor(epoch(ts)) - floor(epoch(lag(ts) OVER w)))::BIGINT AS gap_s, lead(event_id) OVER w AS following,
    (ntile(4) OVER w)::INTEGER AS quarter, (dense_rank() OVER (PARTITION BY user_id ORDER BY event_type))::INTEGER AS kind,
    first_value(event_id) OVER w AS first_event FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"""),
        "window_range_7d_orders": (window_range_7d_orders, """SELECT o_orderkey, count(*) OVER w AS n_week, round(sum(o_totalprice) OVER w, 2) AS spent
FROM (SELECT *, date_diff('day', DATE '1970-01-01', o_orderdate::DATE) AS d FROM orders) WINDOW w AS (PARTITION BY o_custkey ORDER BY d RANGE BETWEEN 6 PRECEDING AND CURRENT ROW)"""),
        "topk_largest_groups": (topk_largest_groups, O.with_(part, "SELECT hash, count(*) AS n FROM v GROUP BY hash ORDER BY n DESC, hash LIMIT 10")),
        "topk_per_split": (topk_per_split, f"SELECT split, doc_id, nth::INTEGER AS nth FROM (SELECT split, doc_id, rank() OVER (PARTITION BY split ORDER BY n_chars DESC, doc_id) AS nth FROM {docs}) WHERE nth <= 5"),
        "setop_intersect_hashes": (setop_intersect_hashes, O.with_(part, "SELECT hash FROM v WHERE split = 'train' INTERSECT SELECT hash FROM v WHERE split = 'test'")),
        "setop_except_hashes": (setop_except_hashes, O.with_(part, "SELECT hash FROM v WHERE split = 'test' EXCEPT ALL SELECT hash FROM v WHERE split = 'train'")),
        "setop_union_collections": (setop_union_collections, O.with_(f"""{page}, bras AS MATERIALIZED (SELECT image_id, 'x' AS split, g FROM ({O.RASTERS['benchmark']})),
{O.block_ctes('bras', 'bblk')}, {O.version_ctes('mean_ac', block='bblk', out='bv')}""",
            "SELECT hash, count(*) AS n FROM (SELECT hash FROM v UNION ALL SELECT hash FROM bv) GROUP BY hash")),
        "string_hash_format": (string_hash_format, O.with_(page, f"""SELECT image_id, x[1:4] AS head, lpad(bin(hash & 15), 4, '0') AS tail, 64 AS bytes,
    levenshtein(x[1:4], x[5:8])::INTEGER AS edits FROM (SELECT *, {hexed} AS x FROM v)""")),
        "string_normalized_duplicates": (string_normalized_duplicates, "SELECT md5(trim(regexp_replace(lower(text), '[^a-z]+', ' ', 'g'))) AS digest, min(doc_id) AS group_id, count(*) AS n FROM documents GROUP BY 1 HAVING count(*) > 1"),
        "date_activity_cells": (date_activity_cells, """SELECT day(ts)::INTEGER AS day, hour(ts)::INTEGER AS hour, date_trunc('month', ts)::DATE AS month, count(*) AS n,
    max(date_diff('day', DATE '2024-01-01', ts::DATE))::INTEGER AS days FROM events GROUP BY ALL"""),
        "bitwise_hamming_profile": (bitwise_hamming_profile, O.with_(page, "SELECT bit_count(xor(hash, (SELECT arg_min(hash, image_id) FROM v)))::INTEGER AS distance, count(*) AS n FROM v GROUP BY 1")),
        "array_orientation_overlap": (array_orientation_overlap, O.with_(O.hashed("part", ops=PAPER_OPS), """SELECT image_id, count(DISTINCT hash)::INTEGER AS n_distinct, min(hash) AS least,
    list_contains(list(hash) FILTER (nth > 0), any_value(hash) FILTER (nth = 0)) AS symmetric FROM v GROUP BY image_id""")),
        "map_group_sizes": (map_group_sizes, O.with_(part, "SELECT hash, string_agg(split, '+' ORDER BY split) AS splits, count(*)::INTEGER AS n_splits FROM (SELECT DISTINCT hash, split FROM v) GROUP BY hash")),
        "json_event_props": (json_event_props, "SELECT event_type, sum((props->>'k')::BIGINT)::BIGINT AS k, sum((props->>'k')::BIGINT)::BIGINT AS k_path, sum((props->>'k')::BIGINT)::BIGINT AS k_variant FROM events GROUP BY 1"),
        "stream_tumbling_events": (stream_tumbling_events, f"SELECT {start.format('time_bucket(INTERVAL 6 HOUR, ts)')}, event_type, count(*) AS n FROM events GROUP BY ALL"),
        "stream_sliding_events": (stream_sliding_events, """SELECT strftime(w, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (
    SELECT time_bucket(INTERVAL 6 HOUR, ts) - to_hours(6 * k) AS w FROM events, range(4) AS r(k)) GROUP BY 1"""),
        "stream_session_events": (stream_session_events, """SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (
    SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (
        SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 8 HOUR THEN 0 ELSE 1 END AS fresh FROM events))
GROUP BY user_id, session"""),
        "stream_dedup_events": (stream_dedup_events, "SELECT DISTINCT props FROM events"),
        "stream_leak_guard": (stream_leak_guard, O.with_(doc, """SELECT v.image_id, v.hash, t.hash IS NOT NULL AS leaks, t.known_id
FROM v LEFT JOIN (SELECT hash, min(image_id) AS known_id FROM v WHERE split = 'train' GROUP BY hash) AS t USING (hash) WHERE v.split <> 'train'""")),
        "stream_first_seen_state": (stream_first_seen_state, "SELECT user_id AS key, count(*) AS n, strftime(min(ts), '%Y-%m-%d %H') AS first_hour FROM events GROUP BY 1"),
        "udf_phash_sql": (udf_phash_sql, O.with_(f"{page}, {O.ahash_cte()}", "SELECT image_id, v.hash, ah.hash AS average, bit_count(xor(v.hash, ah.hash))::INTEGER AS apart FROM v JOIN ah USING (image_id)")),
        "udtf_orientations": (udtf_orientations, O.with_(O.hashed("pages", ops=PAPER_OPS), "SELECT image_id, op, hash FROM v")),
        "udaf_bit_balance": (udaf_bit_balance, O.with_(page, "SELECT split, round(avg(bit_count(hash)), 6) AS mean_bits FROM v GROUP BY split")),
        "sql_leakage_report": (sql_leakage_report, O.with_(part, f"SELECT search, target, n_search, n_hits FROM ({O.matrix('v', 'v', 'oo', False)})")),
    }
