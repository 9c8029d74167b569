"""DuckDB twins of the corpus queries that SQL can express."""

from __future__ import annotations

from splitguard.llm import decontam, secrets, sharding


def _quoted(text: str) -> str:
    return text.replace("'", "''")


def _secrets() -> str:
    def found(kind: int, pattern: str, value: int) -> str:
        anchored = _quoted(f"(?s)(.*?)({pattern})")
        return f"""
    SELECT rid, doc_id, repo, {kind} AS kind,
           unnest(regexp_extract_all(body, '{anchored}', 0)) AS whole,
           unnest(regexp_extract_all(body, '{anchored}', 2)) AS hit,
           unnest(regexp_extract_all(body, '{anchored}', {value})) AS val,
           unnest(range(len(regexp_extract_all(body, '{anchored}', 0)))) AS nth
    FROM docs"""

    parts = " UNION ALL ".join(
        [
            found(0, secrets.ASSIGN, 3),
            found(1, secrets.ACCESS, 2),
            found(2, secrets.HEX, 2),
            found(3, secrets.MIXED, 2),
        ]
    )
    names = ", ".join(f"'{k}'" for k in secrets.KINDS)
    return f"""
WITH docs AS (
    SELECT row_number() OVER () AS rid, doc_id, source AS repo, coalesce(text, '') AS body
    FROM documents
), raw AS ({parts}
), placed AS (
    SELECT *, sum(length(whole)) OVER (PARTITION BY rid, kind ORDER BY nth) AS fin FROM raw
), spans AS (
    SELECT rid, doc_id, repo, kind, fin - length(hit) AS start, fin, val FROM placed
), base AS (
    SELECT * FROM spans WHERE kind IN (1, 2) OR (kind = 0 AND length(val) >= {secrets.LEAST_VALUE})
), mixed AS (
    SELECT * FROM spans AS m
    WHERE kind = 3 AND regexp_matches(val, '[a-z]') AND regexp_matches(val, '[A-Z]')
      AND regexp_matches(val, '[0-9]')
      AND NOT EXISTS (SELECT 1 FROM base AS b WHERE b.rid = m.rid AND b.start < m.fin AND m.start < b.fin)
), cand AS (
    SELECT * FROM base UNION ALL SELECT * FROM mixed
), owned AS (
    SELECT val, count(DISTINCT coalesce(split_part(repo, '/', 1), chr(1))) AS owners,
           count(DISTINCT coalesce(repo, chr(1))) AS repos FROM cand GROUP BY val
), judged AS (
    SELECT c.*, o.owners, o.repos, o.owners <= {secrets.LIVE_OWNERS} AND o.repos <= {secrets.LIVE_REPOS} AS live
    FROM cand AS c JOIN owned AS o USING (val)
), kept AS (
    SELECT *, ([{names}])[kind + 1] || ':' || start::BIGINT || ':' || fin::BIGINT AS span
    FROM judged WHERE kind < 3 OR live
), per AS (
    SELECT rid, count(*) FILTER (kind = 0) AS n_assign, count(*) FILTER (kind = 1) AS n_access,
           count(*) FILTER (kind = 2) AS n_hex,
           string_agg(span, ',' ORDER BY start, kind) FILTER (kind < 3) AS base_spans,
           string_agg(span, ',' ORDER BY start, kind) AS spans,
           count(*) FILTER (live) AS n_live, count(*) FILTER (NOT live) AS n_copied
    FROM kept GROUP BY rid
), most AS (
    SELECT rid, max(owners) AS most_owners, max(repos) AS most_repos FROM judged GROUP BY rid
)
SELECT d.doc_id, coalesce(n_assign, 0)::BIGINT AS n_assign, coalesce(n_access, 0)::BIGINT AS n_access,
       coalesce(n_hex, 0)::BIGINT AS n_hex, sha256(coalesce(base_spans, '')) AS base_sha256,
       coalesce(spans, '') AS spans, coalesce(n_live, 0)::BIGINT AS n_live,
       coalesce(n_copied, 0)::BIGINT AS n_copied, coalesce(most_owners, 0)::BIGINT AS most_owners,
       coalesce(most_repos, 0)::BIGINT AS most_repos
FROM docs AS d LEFT JOIN per USING (rid) LEFT JOIN most USING (rid)"""


def _shards() -> str:
    n = sharding.SHARDS
    step = "CASE WHEN c % 2 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END"
    rounds = "range(256)"
    for _ in range(8):
        rounds = f"list_transform({rounds}, lambda c: {step})"
    return f"""
WITH crc AS MATERIALIZED (
    SELECT {rounds} AS steps
), docs AS (
    SELECT doc_id, list_transform(regexp_extract_all(hex(encode(coalesce(text, ''))), '..'),
                                  lambda h: ('0x' || h)::BIGINT) AS octets FROM documents
), slim AS (
    SELECT doc_id, (len(octets) + {sharding.ROW_BYTES})::BIGINT AS size,
           xor(list_reduce(list_prepend(4294967295::BIGINT, octets),
                lambda r, b: xor(r >> 8, steps[(xor(r, b) & 255) + 1])), 4294967295::BIGINT) AS text_crc32
    FROM docs, crc
), summed AS (
    SELECT *, sum(size) OVER (ORDER BY doc_id, size, text_crc32 ROWS UNBOUNDED PRECEDING) AS upto,
           sum(size) OVER () AS whole FROM slim
), placed AS (
    SELECT *, least({n - 1}, ((2 * upto - size) * {n}) // (2 * whole))::INTEGER AS shard FROM summed
)
SELECT doc_id, size, text_crc32, 'bytes' AS law, shard,
       row_number() OVER (PARTITION BY shard ORDER BY doc_id, size, text_crc32) - 1 AS slot,
       CAST(NULL AS INTEGER) AS grown_shard
FROM placed"""


def _contamination() -> str:
    words = (
        "regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', "
        "'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+')"
    )
    size = decontam.WORDS
    return f"""
WITH items AS (
    SELECT item_id, {words} AS w FROM benchmark
), wins AS (
    SELECT DISTINCT item_id, k, array_to_string(w[i + 1 : i + k], ' ') AS win
    FROM (SELECT item_id, w, least({size}, len(w)) AS k,
                 unnest(range(len(w) - least({size}, len(w)) + 1)) AS i FROM items WHERE len(w) > 0)
), docs AS (
    SELECT row_number() OVER () AS rid, doc_id, {words} AS w FROM documents
), sizes AS (
    SELECT DISTINCT k FROM wins
), grams AS (
    SELECT rid, k, i, array_to_string(w[i + 1 : i + k], ' ') AS win
    FROM (SELECT rid, w, k, unnest(range(len(w) - k + 1)) AS i FROM docs, sizes WHERE len(w) >= k)
), occ AS (
    SELECT g.rid, g.k, g.i, wins.item_id FROM grams AS g JOIN wins ON g.k = wins.k AND g.win = wins.win
), hits AS (
    SELECT rid, count(DISTINCT i + j) AS n_hit
    FROM (SELECT rid, i, unnest(range(k)) AS j FROM occ) GROUP BY rid
), found AS (
    SELECT rid, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS ids
    FROM (SELECT DISTINCT rid, item_id::VARCHAR AS item FROM occ) GROUP BY rid
)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit,
       coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(ids, '')) AS items_sha256,
       coalesce(n_hit, 0) > 0 AS contaminated
FROM docs LEFT JOIN hits USING (rid) LEFT JOIN found USING (rid)"""


def _exact() -> str:
    return """
WITH docs AS (
    SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]+', ' ', 'g')) AS h,
           row_number() OVER () AS rid FROM documents
)
SELECT doc_id, min(doc_id) OVER (PARTITION BY h) AS keep_id,
       count(*) OVER (PARTITION BY h) AS group_size,
       row_number() OVER (PARTITION BY h ORDER BY doc_id, rid) = 1 AS kept, h AS text_sha256
FROM docs"""


def oracles() -> dict[str, str]:
    return {
        "op1_secret_scan": _secrets(),
        "op3_byte_shards": _shards(),
        "op8_decontamination": _contamination(),
        "op9_exact_dedup": _exact(),
    }
