"""The operators' queries, and their SQL where SQL can express them."""

from __future__ import annotations

from .bytebpe import op4_byte_bpe
from .dedup import op5_exact_dedup
from .html import op8_html_extraction
from .licenses import op1_license_scan
from .neardup import op9_near_dedup
from .packing import op6_packing
from .quality import op2_quality
from .sharding import op3_sharding
from .tokenfiles import op10_token_files
from .topk import op7_exact_topk

QUERIES = {f.__name__: f for f in (op1_license_scan, op2_quality, op3_sharding, op4_byte_bpe, op5_exact_dedup, op6_packing, op7_exact_topk, op8_html_extraction, op9_near_dedup, op10_token_files)}

ORACLES = {
    # the checksum byte by byte: eight steps of the reflected polynomial a byte, folded over the text's bytes
    "op3_sharding": """
        WITH RECURSIVE steps AS (SELECT b, b AS c, 0 AS i FROM range(0, 256) t(b) UNION ALL SELECT b, CASE WHEN c % 2 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END, i + 1 FROM steps WHERE i < 8),
        tab AS (SELECT list(c ORDER BY b) AS t FROM steps WHERE i = 8),
        d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h, octet_length(encode(coalesce(text, ''))) AS n FROM documents),
        s AS (SELECT doc_id, n + 16 AS size, xor(list_reduce(range(0, n), lambda c, i: xor(t[xor(c & 255, ('0x' || substr(h, 2 * i + 1, 2))::BIGINT) + 1], c >> 8), 4294967295::BIGINT), 4294967295) AS text_crc32 FROM d, tab),
        p AS (SELECT *, sum(size) OVER (ORDER BY doc_id) - size AS start, sum(size) OVER () AS total FROM s),
        q AS (SELECT *, least(39, (start * 40) // total)::INTEGER AS shard FROM p)
        SELECT doc_id, size::BIGINT AS size, text_crc32::BIGINT AS text_crc32, 'bytes' AS law, shard, row_number() OVER (PARTITION BY shard ORDER BY doc_id) - 1 AS slot, NULL::INTEGER AS grown_shard FROM q""",
    "op5_exact_dedup": """
        SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, sha256(coalesce(text, '')) AS text_sha256
        FROM documents WINDOW w AS (PARTITION BY coalesce(text, ''))""",
    "op7_exact_topk": """
        WITH v AS (
            SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS v FROM embeddings
            WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
        s AS (
            SELECT q.vec_id AS query_id, c.vec_id AS vec_id, list_inner_product(q.v, c.v)::BIGINT AS score
            FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0)
        SELECT query_id, (row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id))::INTEGER AS rank, vec_id, score
        FROM s QUALIFY rank <= 5""",
}
