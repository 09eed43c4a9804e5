"""DuckDB SQL for the queries that SQL can express on whole tables."""

ORACLES: dict[str, str] = {
    "op6_exact_dedup": """
        WITH d AS (SELECT doc_id, coalesce(text, '') AS body FROM documents),
        g AS (SELECT body, max(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY body)
        SELECT doc_id, keep_id, group_size, doc_id IS NOT DISTINCT FROM keep_id AS kept, sha256(body) AS text_sha256
        FROM d JOIN g USING (body)""",
    "op1_decontaminate": r"""
        WITH w AS (SELECT doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), []) AS words FROM documents),
        i AS (SELECT item_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), []) AS words FROM benchmark),
        iw AS (SELECT DISTINCT item_id, list_slice(words, k, k + n - 1) AS win, n FROM (SELECT item_id, words, least(13, len(words)) AS n, unnest(range(1, greatest(1, len(words) - 12) + 1)) AS k FROM i WHERE len(words) > 0)),
        sizes AS (SELECT DISTINCT n FROM iw),
        dw AS (SELECT doc_id, k, n, list_slice(words, k, k + n - 1) AS win FROM (SELECT doc_id, words, n, unnest(range(1, len(words) - n + 2)) AS k FROM w, sizes WHERE len(words) >= n)),
        hits AS (SELECT doc_id, k, n, item_id FROM dw JOIN iw USING (n, win)),
        hw AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(k, k + n)) AS p FROM (SELECT DISTINCT doc_id, k, n FROM hits)) GROUP BY 1),
        hi AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM hits) GROUP BY 1)
        SELECT w.doc_id, CAST(len(words) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256,
               coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(words) AS contaminated
        FROM w LEFT JOIN hw USING (doc_id) LEFT JOIN hi USING (doc_id)""",
    "op4_minhash": r"""
        WITH RECURSIVE w AS (SELECT doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+'), []) AS words FROM documents),
        s AS (SELECT DISTINCT doc_id, list_slice(words, k, k + 4) AS sh FROM (SELECT doc_id, words, unnest(range(1, greatest(1, len(words) - 4) + 1)) AS k FROM w WHERE len(words) > 0)),
        n AS (SELECT doc_id, count(*) AS n_shingles FROM s GROUP BY 1),
        p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS both_n FROM s a JOIN s b ON a.sh = b.sh AND a.doc_id <> b.doc_id GROUP BY 1, 2),
        e AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * both_n >= 75 * (x.n_shingles + y.n_shingles - both_n)),
        r AS (SELECT doc_id, doc_id AS other FROM w UNION SELECT r.doc_id, e.b FROM r JOIN e ON e.a = r.other),
        c AS (SELECT doc_id, min(other) AS component_id FROM r GROUP BY 1)
        SELECT w.doc_id, coalesce(n_shingles, 0) AS n_shingles, component_id, w.doc_id = component_id AS kept FROM w JOIN c USING (doc_id) LEFT JOIN n USING (doc_id)""",
    "op7_substring": r"""
        WITH w AS (SELECT doc_id, coalesce(regexp_extract_all(text, '[^\x20\x09-\x0D]+'), []) AS words FROM documents),
        g AS (SELECT doc_id, k, list_slice(words, k, k + 19) AS win FROM (SELECT doc_id, words, unnest(range(1, len(words) - 18)) AS k FROM w WHERE len(words) >= 20)),
        f AS (SELECT doc_id, k, row_number() OVER (PARTITION BY win ORDER BY doc_id, k) AS nth FROM g),
        c AS (SELECT DISTINCT doc_id, unnest(range(k, k + 20)) AS p FROM f WHERE nth > 1),
        a AS (SELECT doc_id, p, words[p] AS word FROM (SELECT doc_id, words, unnest(range(1, len(words) + 1)) AS p FROM w)),
        k AS (SELECT a.doc_id, string_agg(word, ' ' ORDER BY p) AS kept, count(*) AS n_kept FROM a ANTI JOIN c ON a.doc_id = c.doc_id AND a.p = c.p GROUP BY 1)
        SELECT w.doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(len(words) - coalesce(n_kept, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
        FROM w LEFT JOIN k USING (doc_id)""",
    "op8_suffix_array": r"""
        WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
        g AS (SELECT doc_id, k, substr(h, 2 * k - 1, 100) AS s FROM (SELECT doc_id, h, unnest(range(1, CAST(len(h) / 2 AS BIGINT) - 48)) AS k FROM d WHERE len(h) >= 100)),
        f AS (SELECT s, min(doc_id) AS first FROM g GROUP BY 1 HAVING min(doc_id) < max(doc_id)),
        w AS (SELECT g.doc_id, g.k FROM g JOIN f USING (s) WHERE g.doc_id > f.first),
        l AS (SELECT doc_id, k, lag(k) OVER (PARTITION BY doc_id ORDER BY k) AS before FROM w),
        r AS (SELECT doc_id, k, sum(CASE WHEN before IS NULL OR k > before + 50 THEN 1 ELSE 0 END) OVER (PARTITION BY doc_id ORDER BY k) AS span FROM l),
        sp AS (SELECT doc_id, span, min(k) AS a, max(k) + 50 AS b FROM r GROUP BY 1, 2),
        gaps AS (SELECT doc_id, span, a, b, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY span), 1) AS from_k FROM sp),
        p AS (SELECT doc_id, string_agg(substr(h, 2 * from_k - 1, 2 * (a - from_k)), '' ORDER BY span) AS head, sum(b - a) AS n_removed, count(*) AS n_spans, max(b) AS last FROM gaps JOIN d USING (doc_id) GROUP BY 1)
        SELECT d.doc_id, CAST(len(h) / 2 AS BIGINT) AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, coalesce(n_spans, 0) AS n_spans,
               sha256(unhex(coalesce(head || substr(h, 2 * last - 1), h))) AS kept_sha256
        FROM d LEFT JOIN p USING (doc_id)""",
    "op5_tool_calls": r"""
        WITH RECURSIVE m AS (SELECT conv_id, turn, role, text, CASE role WHEN 'user' THEN turn WHEN 'assistant' THEN turn - 1 END AS asked FROM conversations),
        r AS (SELECT *, CASE WHEN role = 'user' THEN 'call' WHEN asked >= 0 THEN 'result' ELSE 'message' END AS kind, CASE WHEN asked >= 0 THEN 'c' || conv_id || '-' || asked END AS call_id FROM m),
        c AS (SELECT conv_id, asked, min(turn) AS call_turn FROM r WHERE kind = 'call' GROUP BY 1, 2),
        a AS (SELECT conv_id, asked, min(turn) AS result_turn FROM r WHERE kind = 'result' GROUP BY 1, 2),
        needs AS (SELECT conv_id, asked, CASE WHEN asked // 2 % 3 = 2 THEN asked // 2 + 1 ELSE asked // 2 // 2 END * 2 + asked % 2 AS needed FROM c WHERE asked >= 2),
        ch AS (SELECT conv_id, asked, needed, 1 AS depth FROM needs UNION ALL SELECT ch.conv_id, ch.asked, n.needed, depth + 1 FROM ch JOIN needs n ON n.conv_id = ch.conv_id AND n.asked = ch.needed),
        lv AS (SELECT ch.conv_id, ch.asked, max(depth) AS level, max(greatest(call_turn, result_turn)) AS late
               FROM ch LEFT JOIN c ON c.conv_id = ch.conv_id AND c.asked = needed LEFT JOIN a ON a.conv_id = ch.conv_id AND a.asked = needed GROUP BY 1, 2),
        j AS (SELECT r.*, call_turn, result_turn, coalesce(level, 0) AS level, CASE WHEN kind = 'message' THEN turn ELSE greatest(late, call_turn, turn) END AS place
              FROM r LEFT JOIN c USING (conv_id, asked) LEFT JOIN a USING (conv_id, asked) LEFT JOIN lv USING (conv_id, asked)),
        o AS (SELECT conv_id, turn, kind, call_id, level, place,
                CASE WHEN kind = 'message' THEN 'message' WHEN turn <> CASE kind WHEN 'call' THEN call_turn ELSE result_turn END THEN 'repeated' WHEN call_turn IS NULL THEN 'orphan' WHEN result_turn IS NULL THEN 'unanswered' ELSE 'linked' END AS status,
                kind <> 'call' OR text IS NOT NULL AS valid,
                CASE WHEN kind = 'call' THEN '{"arguments":{"prompt":' || to_json(text) || ',"words":' || len(regexp_extract_all(text, '[^\s]+')) || '},"id":' || to_json(call_id) || ',"name":"reply","role":' || to_json(role) || '}'
                     ELSE '{"content":' || to_json(text) || ',"id":' || coalesce(CAST(to_json(call_id) AS VARCHAR), 'null') || ',"role":' || to_json(role) || '}' END AS line
              FROM j)
        SELECT conv_id, turn, kind, call_id, status, valid, line,
               row_number() OVER (PARTITION BY conv_id ORDER BY place, level, kind = 'result', turn, call_id NULLS FIRST, line) - 1 AS position FROM o""",
}
