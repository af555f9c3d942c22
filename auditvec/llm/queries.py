"""Queries over the given tables, one per operator, and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from . import bitslice, linechunks, quality, sharding, token_counts, toxicity, warc
from .decontam import scan_documents
from .lshforest import near_duplicates
from .mixing import mix_plan
from .shared import new_path, table

TOKENIZER = "byte_bpe_50k.json"


def op1_sharding(spark, sf_dir):
    return sharding.assign_shards(table(spark, sf_dir, "documents").select("doc_id"))


def op2_toxicity(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return toxicity.score_toxicity(docs, toxicity.train(docs, table(spark, sf_dir, "labels")))


def op3_quality(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return quality.score_quality(docs, quality.train(docs, table(spark, sf_dir, "labels")))


def op4_token_counts(spark, sf_dir):
    import public_tokenizers

    return token_counts.count_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path(TOKENIZER), new_path(spark, "token-counts"))


def op5_topk_search(spark, sf_dir):
    return bitslice.top_k(table(spark, sf_dir, "embeddings"))


def op6_warc(spark, sf_dir):
    return warc.deduplicated_archives(table(spark, sf_dir, "pages"), new_path(spark, "warc"))


def op8_near_duplicates(spark, sf_dir):
    return near_duplicates(table(spark, sf_dir, "documents"), width=3, least=(85, 100))


def op10_line_dedup(spark, sf_dir):
    return linechunks.dedup_lines(table(spark, sf_dir, "documents"))


def op7_decontamination(spark, sf_dir):
    return scan_documents(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op9_mixing(spark, sf_dir):
    return mix_plan(table(spark, sf_dir, "documents"))


def _walks() -> str:
    return ", ".join("(%d, %d, %d)" % (i, *sharding.preference(f"shard-{i}", sharding.TABLE_SIZE)) for i in range(sharding.SHARDS))


# The table is filled again here, turn by turn, from the shards' starts and steps.
OP1 = f"""
WITH RECURSIVE walk(shard, start, step) AS (VALUES {_walks()}),
lists AS (SELECT list(start ORDER BY shard) AS starts, list(step ORDER BY shard) AS steps FROM walk),
claim(turn, owner, jump) AS (
  SELECT 0, list_transform(range({sharding.TABLE_SIZE}), lambda x: -1), list_transform(range({sharding.SHARDS}), lambda x: 0) FROM lists
  UNION ALL
  SELECT turn + 1,
         list_transform(owner, lambda o, i: CASE WHEN i - 1 = slot THEN s ELSE o END),
         list_transform(jump, lambda j, i: CASE WHEN i - 1 = s THEN free + 1 ELSE j END)
  FROM (SELECT *, (starts[s + 1] + free * steps[s + 1]) % {sharding.TABLE_SIZE} AS slot
        FROM (SELECT *, list_filter(range(jump[s + 1], {sharding.TABLE_SIZE}),
                     lambda j: owner[(starts[s + 1] + j * steps[s + 1]) % {sharding.TABLE_SIZE} + 1] = -1)[1] AS free
              FROM (SELECT turn, owner, jump, starts, steps, turn % {sharding.SHARDS} AS s FROM claim, lists
                    WHERE turn < {sharding.TABLE_SIZE})))
),
filled AS (SELECT owner FROM claim WHERE turn = {sharding.TABLE_SIZE}),
slots AS (SELECT unnest(range({sharding.TABLE_SIZE})) AS slot, unnest(owner) AS shard_id FROM filled),
placed AS (SELECT doc_id, ('0x' || substr(md5('{sharding.SEED}|' || coalesce(doc_id::VARCHAR, 'null')), 1, 15))::BIGINT % {sharding.TABLE_SIZE} AS slot FROM documents)
SELECT doc_id, placed.slot::BIGINT AS slot, shard_id::BIGINT AS shard_id FROM placed JOIN slots ON placed.slot = slots.slot
"""

OP7 = r"""
WITH item AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM benchmark),
gram AS (
  SELECT DISTINCT item_id, n, array_to_string(w[i:i + n - 1], ' ') AS g
  FROM (SELECT item_id, w, least(len(w), 13) AS n, unnest(range(1, len(w) - least(len(w), 13) + 2)) AS i FROM item WHERE len(w) > 0)),
doc AS (
  SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM documents),
place AS (
  SELECT r, i, n, array_to_string(w[i:i + n - 1], ' ') AS g
  FROM (SELECT r, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM doc, (SELECT DISTINCT n FROM gram) WHERE len(w) >= n)),
hit AS (SELECT r, i, place.n, item_id FROM place JOIN gram USING (g)),
word AS (SELECT r, count(DISTINCT p) AS n_hit FROM (SELECT r, unnest(range(i, i + n)) AS p FROM hit) GROUP BY r),
named AS (SELECT r, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS names FROM (SELECT DISTINCT r, item_id::VARCHAR AS item FROM hit WHERE item_id IS NOT NULL) GROUP BY r)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM doc LEFT JOIN word USING (r) LEFT JOIN named USING (r)
"""

OP9 = r"""
WITH RECURSIVE doc AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
         ('0x' || substr(md5('7|' || coalesce(doc_id::VARCHAR, 'null')), 1, 15))::BIGINT AS k
  FROM documents),
src AS (
  SELECT source, sum(size)::BIGINT AS size, [5, 2, 1][(row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1] AS w
  FROM doc GROUP BY source),
-- Reshare what the full sources leave, round by round, until no target is above its limit.
share(round, full_ones) AS (
  SELECT 0, ARRAY[]::VARCHAR[]
  UNION ALL
  SELECT round + 1, more FROM (
    SELECT round, full_ones, (
      SELECT coalesce(list(coalesce('s' || source, 'n')), ARRAY[]::VARCHAR[]) FROM src
      WHERE list_contains(full_ones, coalesce('s' || source, 'n')) OR 3 * size * (SELECT sum(w) FROM src WHERE NOT list_contains(full_ones, coalesce('s' || source, 'n')))
            <= w * ((SELECT sum(size) FROM src) - (SELECT coalesce(sum(3 * size), 0) FROM src WHERE list_contains(full_ones, coalesce('s' || source, 'n'))))) AS more
    FROM share) WHERE len(more) > len(full_ones)),
fin AS (SELECT full_ones FROM share ORDER BY round DESC LIMIT 1),
goal AS (
  SELECT source, size, CASE WHEN list_contains(full_ones, coalesce('s' || source, 'n')) THEN (3 * size)::DOUBLE
    ELSE (w * ((SELECT sum(size) FROM src) - (SELECT coalesce(sum(3 * size), 0) FROM src, fin WHERE list_contains(full_ones, coalesce('s' || source, 'n')))))::DOUBLE
         / (SELECT sum(w) FROM src, fin WHERE NOT list_contains(full_ones, coalesce('s' || source, 'n')))::DOUBLE END AS target
  FROM src, fin),
placed AS (
  SELECT doc.*, goal.size AS source_size, target, floor(target + 0.5)::BIGINT AS budget,
         coalesce(sum(doc.size) OVER (PARTITION BY doc.source ORDER BY k, doc_id NULLS FIRST, doc.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before
  FROM doc JOIN goal ON doc.source IS NOT DISTINCT FROM goal.source)
SELECT doc_id, size, source_size, target,
       (CASE WHEN source_size = 0 THEN 0 ELSE budget // source_size * size + least(size, greatest(0, budget % source_size - before)) END)::BIGINT AS taken
FROM placed
"""

OP5 = """
WITH vec AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS q FROM embeddings
  WHERE vec_id IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
scored AS (
  SELECT a.vec_id AS query_id, b.vec_id, list_sum(list_transform(list_zip(a.q, b.q), lambda p: p[1] * p[2]))::BIGINT AS score
  FROM vec a JOIN vec b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id),
ranked AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS r FROM scored)
SELECT query_id, r::INT AS rank, vec_id, score FROM ranked WHERE r <= 5
"""

OP6 = """
WITH page AS (
  SELECT page_id, coalesce(html, '') AS body, sha1(coalesce(html, '')) AS h FROM pages),
group_of AS (
  SELECT page_id, octet_length(encode(body))::BIGINT AS payload_bytes, max(page_id) OVER (PARTITION BY body) AS top,
         array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
           ((('0x' || substr(h, (i // 4 * 5 + 1)::INT, 5))::INT >> (15 - 5 * (i % 4))::INT) & 31) + 1, 1)), '') AS payload_digest
  FROM page)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id = top THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN page_id <> top THEN top END AS refers_to
FROM group_of
"""

OP8 = r"""
WITH RECURSIVE doc AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
item AS (
  SELECT DISTINCT doc_id, array_to_string(w[i:i + least(3, len(w)) - 1], ' ') AS s
  FROM (SELECT doc_id, w, unnest(range(1, len(w) - least(3, len(w)) + 2)) AS i FROM doc WHERE len(w) > 0)),
size AS (SELECT doc_id, count(*) AS n FROM item GROUP BY doc_id),
link AS (
  SELECT a, b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM item x JOIN item y ON x.s = y.s AND x.doc_id < y.doc_id GROUP BY ALL) p
  JOIN size u ON u.doc_id = a JOIN size v ON v.doc_id = b WHERE 100 * c >= 85 * (u.n + v.n - c)),
both_ways AS (SELECT a, b FROM link UNION SELECT b, a FROM link),
reach AS (SELECT doc_id, doc_id AS r FROM doc UNION SELECT reach.doc_id, b FROM reach JOIN both_ways ON r = a)
SELECT doc.doc_id, coalesce(n, 0)::BIGINT AS n_shingles, c AS component_id, doc.doc_id = c AS kept
FROM doc LEFT JOIN size USING (doc_id) JOIN (SELECT doc_id, min(r) AS c FROM reach GROUP BY doc_id) USING (doc_id)
"""

QUERIES = {
    "op1_sharding": op1_sharding,
    "op2_toxicity": op2_toxicity,
    "op3_quality": op3_quality,
    "op4_token_counts": op4_token_counts,
    "op5_topk_search": op5_topk_search,
    "op6_warc": op6_warc,
    "op7_decontamination": op7_decontamination,
    "op8_near_duplicates": op8_near_duplicates,
    "op9_mixing": op9_mixing,
    "op10_line_dedup": op10_line_dedup,
}
ORACLES = {"op1_sharding": OP1, "op5_topk_search": OP5, "op6_warc": OP6, "op7_decontamination": OP7, "op8_near_duplicates": OP8, "op9_mixing": OP9}
