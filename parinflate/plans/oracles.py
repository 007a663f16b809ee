"""What the catalogue must give, as SQL over the source tables; nothing here reads the engine's files."""

from __future__ import annotations

DOCS = "SELECT doc_id, md5(text) AS text_md5, octet_length(encode(text)) AS n_bytes, lang, source FROM documents"
DAYS = "strftime(l_shipdate, '%Y-%m-%d')"
HEX = "md5(l_orderkey::VARCHAR || ':' || l_linenumber::VARCHAR)"
#: A request's record and count over n records, as the engine's workload makes them.
ASK = "SELECT event_id AS request_id, (event_id * 7919 + user_id) % n AS record, least(event_id % {most} + 1, n - (event_id * 7919 + user_id) % n) AS k FROM events, (SELECT count(*) AS n FROM lineitem)"
FILE = f"SELECT row_number() OVER (ORDER BY l_orderkey, l_linenumber) - 1 AS record, to_base64(unhex({HEX})) AS line FROM lineitem"
BYTE = "('0x' || substr(h, 2 * ({0}) + 1, 2))::INT"
CASCADE = f"""WITH b AS (SELECT md5(o_orderkey::VARCHAR) AS h FROM orders), v AS (SELECT {BYTE.format("k")} + 256 * {BYTE.format("k + 1")} AS v FROM b, range(15) t(k)),
w AS (SELECT v >> r::INT AS w FROM v, range(8) t(r)), s AS (SELECT CASE WHEN w & 1 = 1 THEN 'final_bit' WHEN (w >> 1) & 3 <> 2 THEN 'block_type' WHEN (w >> 3) & 31 >= 30 THEN 'literal_count' ELSE 'passed' END AS step FROM w)
SELECT step, count(*) AS n FROM s GROUP BY step"""
READ = f"""WITH f AS ({FILE}), a AS ({{ask}}) SELECT a.request_id, string_agg(f.line || chr(10), '' ORDER BY f.record) AS got FROM a JOIN f ON f.record >= a.record AND f.record < a.record + a.k GROUP BY a.request_id"""
CHUNKS = "SELECT user_id AS reader_id, event_id, floor(abs(value))::BIGINT % 8 AS c, lag(floor(abs(value))::BIGINT % 8) OVER (PARTITION BY user_id ORDER BY event_id) AS p FROM events"


def _hits(condition: str) -> str:
    return f"WITH t AS ({CHUNKS}) SELECT reader_id, count(*) AS accesses, count(*) FILTER ({condition}) AS hits, count(*) - count(*) FILTER ({condition}) AS misses FROM t GROUP BY reader_id"


def _field(first: int, width: int) -> str:
    """Bits [first, first + width), at most 32, of the 16 bytes h, least significant first."""
    lo, hi = first // 8, (first + width - 1) // 8
    whole = " + ".join(f"({BYTE.format(k)}::HUGEINT << {8 * (k - lo)})" for k in range(lo, hi + 1))
    return f"((({whole}) >> {first % 8}) & {(1 << width) - 1})"


def _width(w: int) -> str:
    low = " + ".join(_field(w * k, min(w, 32)) for k in range(128 // w))
    high = " + ".join(_field(w * k + 32, w - 32) for k in range(128 // w)) if w > 32 else "0"
    return f"SELECT {w}::INT AS width, sum({low})::BIGINT AS low, sum({high})::BIGINT AS high FROM (SELECT md5(o_orderkey::VARCHAR) AS h FROM orders)"


_BIT = lambda i: f"(({BYTE.format(i // 8)} >> {i % 8}) & 1)"
_LENS = ", ".join(f"{_BIT(3 * k)} + {_BIT(3 * k + 1)} * 2 + {_BIT(3 * k + 2)} * 4" for k in range(19))
_LEVELS = ", ".join(f"('{a}', {b})" for a, b in (("single", 1), ("single", 3), ("single", 9), ("pigz_like", 1), ("bgzf", 9), ("huffman_only", 6), ("rle", 6)))
_SALTED = "md5(l_orderkey::VARCHAR || ':' || l_linenumber::VARCHAR || ':' || salt::VARCHAR)"
_TEXTS = {"documents_text": ("documents", "coalesce(text, '')", "doc_id"), "pages_html": ("pages", "coalesce(html, '')", "page_id"), "conversations_text": ("conversations", "coalesce(text, '')", "conv_id, turn"), "benchmark_text": ("benchmark", "coalesce(text, '')", "item_id"), "nation_name": ("nation", "n_name", "n_nationkey")}
_COLUMNS = {"lineitem": ("l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate::VARCHAR", "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice"), "orders": ("o_orderkey, o_custkey, o_orderstatus, o_totalprice, o_orderdate::VARCHAR, o_orderpriority", "o_orderkey")}
#: (table, line, order) of each member that has lines.
MEMBERS = _TEXTS | {t: (t, f"concat_ws(',', {cols})", key) for t, (cols, key) in _COLUMNS.items()}
_MEMBER = "SELECT 'corpus/{0}' AS name, sum(octet_length(encode({2})) + 1)::BIGINT AS size, md5(string_agg({2} || chr(10), '' ORDER BY {3})) AS content_md5 FROM {1}"
_CSV = "octet_length(encode(concat_ws(',', l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate::VARCHAR)))"

ORACLES: dict[str, str] = {
    "cr_documents_md5": DOCS,
    "cr_pages_len": "SELECT page_id, url, length(html) AS n_chars, md5(html) AS html_md5 FROM pages",
    "cr_conversations_md5": "SELECT conv_id, turn, role, md5(text) AS text_md5 FROM conversations",
    "cr_lineitem_rows": f"SELECT l_orderkey, l_linenumber, l_partkey, round(l_extendedprice * 100)::BIGINT AS price_cents, l_returnflag, {DAYS} AS ship_day FROM lineitem",
    "cr_orders_rows": "SELECT o_orderkey, o_custkey, o_orderstatus, round(o_totalprice * 100)::BIGINT AS price_cents, o_orderpriority FROM orders",
    "cr_events_props": "SELECT event_id, user_id, event_type, props FROM events",
    "cr_level_matrix": f"SELECT layout, level, count(*) AS n, sum(octet_length(encode(text)))::BIGINT AS n_bytes FROM (VALUES {_LEVELS}) v(layout, level), documents GROUP BY layout, level",
    **dict.fromkeys(("cr_fixed_only", "cr_stored_only", "cr_single_dynamic", "cr_multi_member", "cr_bgzf", "cr_sync_flush", "cr_nested_gzip", "serial_vs_scan_windows", "marker_resolve_docs", "serial_stage2_docs", "builtin_codec_lines", "zstd_frames_rows", "bzip2_rows", "bgzf_blocks_lines"), DOCS),
    "cr_small_file": "SELECT n_nationkey, n_name, n_regionkey FROM nation",
    "cr_empty_members": "SELECT n_nationkey, n_name, true AS gz FROM nation",
    "base64_random_rows": f"SELECT to_base64(unhex({HEX})) AS line, count(*) AS n FROM lineitem GROUP BY 1",
    "fastq_records": "SELECT event_id, translate(md5(event_id::VARCHAR), '0123456789abcdef', 'ACGTACGTACGTACGT') AS seq, translate(md5('q' || event_id::VARCHAR), '0123456789abcdef', '!#$%&()*+-/:;<=>') AS quality FROM events",
    "tar_member_sizes": " UNION ALL ".join(_MEMBER.format(m, *how) for m, how in MEMBERS.items()) + " UNION ALL SELECT 'corpus/embeddings', sum(4 * len(embedding))::BIGINT, NULL FROM embeddings",
    "tar_member_read": "SELECT row_number() OVER (ORDER BY vec_id) - 1 AS place, embedding[1]::DOUBLE AS first, embedding[len(embedding)]::DOUBLE AS last, len(embedding) AS dims FROM embeddings",
    "tar_text_only_refused": " UNION ALL ".join(f"SELECT 'corpus/{m}' AS name, coalesce(bool_and(NOT regexp_matches({line}, '[^\\x09-\\x7e]')), true) AS accepted FROM {t}" for m, (t, line, _) in MEMBERS.items()),
    "twin_equals_reference": "SELECT item, true AS same, n - n // 2 AS symbols, n AS total FROM (SELECT 'b' || item_id AS item, octet_length(encode(coalesce(text, ''))) AS n FROM benchmark UNION ALL SELECT 'c' || conv_id || '-' || turn, octet_length(encode(coalesce(text, ''))) FROM conversations)",
    "index_read_ranges": READ.format(ask=ASK.format(most=4)),
    "seek_reader_trace": READ.format(ask=ASK.format(most=4)),
    "zip_member_sizes": " UNION ALL ".join("SELECT '{0}' AS name, sum(octet_length(encode({2})) + 1)::BIGINT AS size, md5(string_agg({2} || chr(10), '' ORDER BY {3})) AS content_md5 FROM {1}".format(m, *MEMBERS[m]) for m in ("nation_name", "benchmark_text")),
    "index_split_points": "SELECT count(*) AS newlines, 25 * count(*) AS n_bytes FROM lineitem",
    "index_respace_points": "SELECT count(*) AS newlines, 25 * count(*) AS n_bytes FROM lineitem",
    "upto_prefix": f"SELECT record, line FROM ({FILE}) WHERE record < 160",
    "line_count": "SELECT count(*) AS newlines FROM lineitem",
    "pushdown_range_scan": "SELECT 25 * (count(*) // 4) AS n_bytes, count(*) // 4 AS newlines FROM lineitem",
    "source_lines": FILE,
    **dict.fromkeys(("source_json", "sink_single", "sink_bgzf", "many_files_docs"), DOCS),
    "source_csv_folder": "SELECT o_orderkey, o_custkey, o_orderstatus, round(o_totalprice * 100)::BIGINT AS price_cents, o_orderpriority FROM orders",
    "marker_share": "SELECT 25 * count(*) AS out_len, true AS has_markers, true AS below_one FROM lineitem",
    "crc_verified_members": "SELECT 0 AS member_no, 25 * count(*) AS n, true AS ok FROM lineitem",
    "recover_after_damage": "SELECT lang, 0 AS wrong FROM documents WHERE lang <> (SELECT min(lang) FROM documents) GROUP BY lang",
    "skip_after_damage": "SELECT 0 AS n_bytes, 0 AS complete",
    "filter_cascade_sql": CASCADE,
    "filter_cascade_engine": CASCADE,
    "finder_variants_agree": "SELECT step, 1 AS \"values\", 3 AS variants FROM (VALUES ('passed'), ('final_bit'), ('block_type'), ('literal_count'), ('precode_invalid'), ('precode_unused'), ('precode_data')) v(step)",
    "stored_false_positives": f"""WITH b AS (SELECT salt::INT AS salt, {_SALTED} AS h, l_orderkey, l_linenumber FROM lineitem, range(12) s(salt)),
w AS (SELECT salt, coalesce(right(lag(h) OVER o, 2), 'ff') || h || coalesce(left(lead(h) OVER o, 8), 'ffffffff') AS h FROM b WINDOW o AS (PARTITION BY salt ORDER BY l_orderkey, l_linenumber)),
p AS (SELECT salt, {BYTE.format("k - 1")} AS z, {BYTE.format("k")} AS a, {BYTE.format("k + 1")} AS b, {BYTE.format("k + 2")} AS c, {BYTE.format("k + 3")} AS d FROM w, range(1, 17) t(k))
SELECT salt, count(*) AS n FROM p WHERE z < 32 AND a + c = 255 AND b + d = 255 GROUP BY salt""",
    "precode_check_counts": f"WITH l AS (SELECT [x FOR x IN [{_LENS}] IF x > 0] AS u FROM (SELECT md5(o_orderkey::VARCHAR) AS h FROM orders)), s AS (SELECT u, list_sum([1 << (15 - x) FOR x IN u]) AS t FROM l) SELECT CASE WHEN len(u) = 0 THEN 'empty' WHEN t > 32768 THEN 'over' WHEN t = 32768 OR u = [1] THEN 'valid' ELSE 'under' END AS kind, count(*) AS n FROM s GROUP BY kind",
    "valid_precode_histograms": f"WITH l AS (SELECT [x FOR x IN [{_LENS}] IF x > 0] AS u FROM (SELECT md5(o_orderkey::VARCHAR) AS h FROM orders)) SELECT len(u)::INT AS codes, count(*) AS n FROM l WHERE list_sum([1 << (7 - x) FOR x IN u]) = 128 OR u = [1] GROUP BY 1",
    "kraft_examples": "WITH l AS (SELECT o_orderkey, [x::INT % 4 FOR x IN string_split(o_orderkey::VARCHAR, '')] AS a FROM orders), u AS (SELECT o_orderkey, [x FOR x IN a IF x > 0] AS u FROM l), s AS (SELECT *, list_sum([1 << (15 - x) FOR x IN u]) AS t FROM u) SELECT o_orderkey, CASE WHEN len(u) = 0 THEN 'empty' WHEN t > 32768 THEN 'over' WHEN t = 32768 OR u = [1] THEN 'valid' ELSE 'under' END AS kind FROM s",
    "packed_add": "SELECT l_orderkey, sum(1::BIGINT << (5 * (l_quantity::BIGINT % 8)))::BIGINT AS packed FROM lineitem GROUP BY l_orderkey",
    "bit_reader_sums": " UNION ALL ".join(_width(w) for w in (1, 2, 4, 8, 15, 16, 32, 57)),
    "striped_read_bytes": f"WITH c AS (SELECT string_agg(line || chr(10), '' ORDER BY record) AS t FROM ({FILE})), p AS (SELECT k, substr(t, k * 131072 + 1, 131072) AS x FROM c, range((length(t) + 131071) // 131072) r(k)) SELECT readers, sum(length(x))::BIGINT AS n_bytes, md5(string_agg(md5(x), '' ORDER BY k)) AS digest FROM p, (VALUES (1), (2), (4)) v(readers) GROUP BY readers",
    "finder_recall": "SELECT name, 0 AS missed, true AS precise FROM (VALUES ('nation'), ('region'), ('orders'), ('events'), ('benchmark_text'), ('conversations')) v(name)",
    "deflate_blocks": "SELECT item_id, octet_length(encode(text)) AS n_bytes FROM benchmark",
    "amdahl_bound": "SELECT name, slot_kib, cores, (slot_kib / 32)::BIGINT AS less_work, ceil(n_bytes / (slot_kib * 1024))::BIGINT AS slots, round(ceil(n_bytes / (slot_kib * 1024)) * 32768 / (ceil(n_bytes / (slot_kib * 1024)) * 32768 + n_bytes / cores), 6) AS serial_share FROM (SELECT lang AS name, sum(octet_length(encode(text)))::BIGINT AS n_bytes FROM documents GROUP BY lang HAVING sum(octet_length(encode(text))) > 0) f, (VALUES (128), (512), (1024), (4096), (32768)) s(slot_kib), (VALUES (1), (16), (48), (64), (128)) c(cores)",
    "seek_cost_bound": "SELECT name, spacing_kib, reads, (reads * spacing_kib * 1024 + asked)::BIGINT AS most_bytes, round((reads * spacing_kib * 1024 + asked) / asked, 6) AS amplification FROM (SELECT lang AS name, count(*) AS reads, sum(octet_length(encode(text)))::BIGINT AS asked FROM documents WHERE octet_length(encode(text)) > 0 GROUP BY lang) f, (VALUES (32), (1024), (4096)) s(spacing_kib)",
    "baseline_bytes": f"SELECT baseline, (SELECT sum({_CSV} + 1)::BIGINT FROM lineitem) AS n_bytes FROM (VALUES ('one_task'), ('helper_threads'), ('text_only_unsynchronised'), ('text_only_synchronised'), ('bgzf'), ('serial_index')) v(baseline)",
    "parquet_codec_rows": "SELECT codec, count(*) AS n, sum(o_orderkey)::BIGINT AS keys FROM orders, (VALUES ('lz4'), ('zstd'), ('snappy'), ('gzip')) v(codec) GROUP BY codec",
    "text_only_range_check": r"SELECT doc_id, NOT regexp_matches(coalesce(text, ''), '[^\x09-\x7e]') AS accepted FROM documents",
    "prefetch_replay_next_k": _hits("WHERE c = p OR c = p + 1 OR c = p + 2"),
    "prefetch_replay_lru": _hits("WHERE c = p"),
    "stream_state_replay": f"WITH t AS ({CHUNKS}) SELECT reader_id, count(*) FILTER (WHERE c = p) AS hits, count(*) - count(*) FILTER (WHERE c = p) AS misses FROM t GROUP BY reader_id",
    "ml_pipeline_quality": "SELECT lang, count(*) AS n, sum(quality)::BIGINT AS good, sum(toxic)::BIGINT AS toxic FROM documents JOIN labels USING (doc_id) GROUP BY lang",
    "star_join_over_gz": "SELECT n_name, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS revenue_cents, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name",
    "cube_over_gz": "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity::BIGINT)::BIGINT AS quantity FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "rollup_over_gz": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "grouping_sets_over_gz": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))",
    "window_running_over_gz": "SELECT o_orderkey, sum(round(o_totalprice * 100)::BIGINT) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING)::BIGINT AS running_cents FROM orders",
    "rank_over_gz": "SELECT o_orderkey, rn FROM (SELECT o_orderkey, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) WHERE rn <= 10",
    "topk_over_gz": "SELECT o_orderkey, round(o_totalprice * 100)::BIGINT AS price_cents FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20",
    "asof_access_point": f"SELECT request_id, record * 25 // 1000 * 1000 AS point FROM ({ASK.format(most=4)})",
    "overlap_ranges": f"SELECT request_id, ((record + k) * 25 - 1) // 1000 - record * 25 // 1000 + 1 AS points FROM ({ASK.format(most=80)})",
    "interval_join_accesses": "SELECT a.event_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_type = 'error' AND epoch_us(a.ts) >= epoch_us(b.ts) AND epoch_us(a.ts) < epoch_us(b.ts) + 3600000000 GROUP BY a.event_id",
    "setops_over_gz": "SELECT 'except' AS op, count(*) AS n FROM (SELECT o_orderkey FROM orders EXCEPT ALL SELECT DISTINCT l_orderkey FROM lineitem) UNION ALL SELECT 'intersect', count(*) FROM (SELECT o_orderkey FROM orders INTERSECT SELECT l_orderkey FROM lineitem) UNION ALL SELECT 'union', count(*) FROM (SELECT o_orderkey FROM orders UNION SELECT l_orderkey FROM lineitem)",
    "semi_anti_over_gz": "SELECT 'semi' AS op, count(*) AS n FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem) UNION ALL SELECT 'anti', count(*) FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)",
    "json_props_over_gz": "SELECT json_extract(props, '$.k')::BIGINT AS k, count(*) AS n FROM events GROUP BY k",
    "string_funcs_over_gz": "SELECT doc_id, upper(lang) AS lang_up, length(text) AS chars, octet_length(encode(text)) AS octets, translate(source, 'src', 'SRC') AS src_up FROM documents",
    "array_funcs_over_gz": "SELECT doc_id, len(string_split(text, chr(10))) AS n_lines, list_max([length(x) FOR x IN string_split(text, chr(10))]) AS longest FROM documents",
    "date_funcs_over_gz": "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n FROM orders GROUP BY y, m",
    "stream_tumbling": "SELECT epoch_us(ts) // 3600000000 * 3600000000 AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT s - k * 3600000000 AS start, count(*) AS n FROM (SELECT epoch_us(ts) // 3600000000 * 3600000000 AS s FROM events), range(2) t(k) GROUP BY 1",
    "stream_late": "SELECT s AS start, count(*) AS n FROM (SELECT epoch_us(ts) // 3600000000 * 3600000000 AS s FROM events) WHERE s + 3600000000 <= (SELECT max(epoch_us(ts)) FROM events) - 600000000 GROUP BY s",
    "stream_gz_lines": "SELECT o_orderkey, o_orderstatus FROM orders",
    "stream_session": "WITH g AS (SELECT user_id, epoch_us(ts) AS us, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w < 1800000000 THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, us, sum(fresh) OVER (PARTITION BY user_id ORDER BY us) AS k FROM g) SELECT user_id, min(us) AS start, count(*) AS n FROM s GROUP BY user_id, k",
}
