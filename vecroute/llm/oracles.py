"""DuckDB twins of the operators that SQL can express, over whole tables."""

from __future__ import annotations

from vecroute.llm import collisions, mixing, sharding
from vecroute.llm.templates import _AFTER

#: A table-driven checksum: entry n of the table follows from n by eight halvings.
_HALVE = "CASE WHEN {0} % 2 = 1 THEN xor(3988292384, {0} // 2) ELSE {0} // 2 END"


def _crc_table() -> str:
    steps, last = [], "c0"
    for k in range(1, 9):
        steps.append(f"c{k} AS (SELECT n, {_HALVE.format('c')} AS c FROM {last})")
        last = f"c{k}"
    return f"c0 AS (SELECT n, CAST(n AS BIGINT) AS c FROM range(256) r(n)), {', '.join(steps)}, crc AS (SELECT list(c ORDER BY n) AS tbl FROM {last})"


def shards_sql(n: int = 8, seed: int = sharding.SEED) -> str:
    text = "coalesce(text, '')"
    crc = f"xor(4294967295, list_reduce(list_prepend(4294967295, list_transform(range(0, octet_length(encode({text}))), lambda i: CAST('0x' || substr(hex(encode({text})), 2 * i + 1, 2) AS BIGINT))), lambda a, b: xor(a >> 8, tbl[(xor(a, b) & 255) + 1])))"
    return f"""WITH {_crc_table()},
d AS (SELECT doc_id, source, CAST(octet_length(encode({text})) + 1 AS BIGINT) AS size, CAST({crc} AS BIGINT) AS text_crc32, coalesce('s' || source, 'n') AS stratum, CAST('0x' || substr(md5('{seed}|' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15) AS BIGINT) AS h FROM documents, crc),
r AS (SELECT *, row_number() OVER (PARTITION BY stratum ORDER BY h, doc_id, size, text_crc32) - 1 AS r, count(*) OVER (PARTITION BY stratum) AS n FROM d),
p AS (SELECT *, row_number() OVER (ORDER BY (2 * r + 1) / CAST(n AS DOUBLE), stratum, r) - 1 AS position, count(*) OVER () AS total FROM r),
s AS (SELECT *, position * {n} // total AS shard FROM p)
SELECT doc_id, size, text_crc32, 'rows' AS law, CAST(shard AS INTEGER) AS shard, CAST(position - (shard * total + {n - 1}) // {n} AS BIGINT) AS slot, CAST(NULL AS INTEGER) AS grown_shard FROM s"""


def collisions_sql(cosine: float = collisions.COSINE) -> str:
    return f"""WITH RECURSIVE x AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings),
ok AS (SELECT * FROM x WHERE v IS NOT NULL AND len(list_filter(v, lambda c: c IS NULL OR NOT isfinite(c))) = 0 AND list_sum(list_transform(v, lambda c: c * c)) > 0),
p AS (SELECT a.vec_id AS a, b.vec_id AS b FROM ok a JOIN ok b ON a.vec_id <> b.vec_id AND len(a.v) = len(b.v) AND list_cosine_similarity(a.v, b.v) >= {cosine}),
reach AS (SELECT vec_id AS a, vec_id AS b FROM x UNION SELECT r.a, p.b FROM reach r JOIN p ON p.a = r.b),
c AS (SELECT a AS vec_id, min(b) AS component_id FROM reach GROUP BY 1),
n AS (SELECT a AS vec_id, count(*) AS n FROM p GROUP BY 1)
SELECT x.vec_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_links, c.component_id, x.vec_id = c.component_id AS kept FROM x JOIN c ON c.vec_id = x.vec_id LEFT JOIN n ON n.vec_id = x.vec_id"""


def chat_sql(hostile: str) -> str:
    """Control strings are counted by the run of text that starts one; each costs one backslash."""
    after = _AFTER.removeprefix("(?=").removesuffix(")")
    pattern = rf"[<\[]\\*({after})"
    extra = "len(regexp_extract_all({0}, '" + pattern + "'))"
    role = "replace(replace(role, '\\', '\\\\'), chr(10), '\\n')"
    return f"""WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations UNION ALL SELECT -1, 0, 'user', '{hostile}' UNION ALL SELECT -1, 1, 'assistant', '{hostile}'),
t AS (SELECT *, 8 + length({role}) + {extra.format(role)} + 1 + length(text) + {extra.format('text')} + 7 + 1 AS chars FROM c)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256, CAST(coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars, sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256, CAST(sum(chars) AS BIGINT) AS formatted_chars FROM t GROUP BY 1"""


def mixing_sql(seed: int = mixing.SEED, block: int = mixing.BLOCK_ROWS, period: int = mixing.PERIOD) -> str:
    """The schedule of one period slot by slot, as a recursion over the blocks done so far."""
    return f"""WITH RECURSIVE d AS (SELECT doc_id, source, coalesce('s' || source, 'n') AS stratum, CAST('0x' || substr(md5('{seed}|' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15) AS BIGINT) AS h FROM documents),
n AS (SELECT stratum, count(*) AS rows, sqrt(count(*)) AS raw FROM d GROUP BY 1),
q AS (SELECT *, count(*) OVER () AS sources, greatest({period}, CAST(pow(2, ceil(log2(4 * count(*) OVER ()))) AS BIGINT)) AS period FROM n),
e AS (SELECT *, (period - sources) * raw / sum(raw) OVER () AS exact FROM q),
w AS (SELECT stratum, period, CAST(1 + floor(exact) + CASE WHEN row_number() OVER (ORDER BY exact - floor(exact) DESC, stratum) <= period - sources - sum(floor(exact)) OVER () THEN 1 ELSE 0 END AS BIGINT) AS slots FROM e),
one AS (SELECT list(stratum ORDER BY stratum) AS names, list(slots ORDER BY stratum) AS a, max(period) AS q FROM w),
run AS (
  SELECT CAST(-1 AS BIGINT) AS t, list_transform(a, lambda x: CAST(0 AS BIGINT)) AS done, CAST(0 AS BIGINT) AS pick, CAST(0 AS BIGINT) AS turn FROM one
  UNION ALL
  SELECT t + 1, list_transform(range(1, len(done) + 1), lambda i: done[i] + CASE WHEN i = chosen THEN 1 ELSE 0 END), chosen, done[chosen] FROM (
    SELECT t, done, list_position(due, list_min(due)) AS chosen FROM (
      SELECT t, done, list_transform(range(1, len(done) + 1), lambda i: CASE WHEN done[i] * q // a[i] <= t + 1 THEN ((done[i] + 1) * q + a[i] - 1) // a[i] ELSE 9223372036854775807 END) AS due FROM run, one WHERE t + 1 < q))),
s AS (SELECT names[pick] AS stratum, turn, t AS lap_slot FROM run, one WHERE t >= 0),
r AS (SELECT d.*, row_number() OVER (PARTITION BY stratum ORDER BY h, doc_id) - 1 AS r FROM d),
b AS (SELECT r.*, w.slots, w.period, r // {block} AS block, r % {block} AS in_block FROM r JOIN w USING (stratum)),
f AS (SELECT doc_id, source, block, block * period // slots AS release, ((block + 1) * period + slots - 1) // slots AS deadline, (block // slots) * period + lap_slot AS slot, in_block FROM b JOIN s ON s.stratum = b.stratum AND s.turn = b.block % b.slots)
SELECT doc_id, source, CAST(block AS BIGINT) AS block, CAST(release AS BIGINT) AS release, CAST(deadline AS BIGINT) AS deadline, CAST(slot AS BIGINT) AS slot, CAST(in_block AS BIGINT) AS in_block, row_number() OVER (ORDER BY slot, in_block) - 1 AS position FROM f"""
