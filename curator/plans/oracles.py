"""DuckDB SQL that checks the queries, composed of named common table expressions."""

from __future__ import annotations

TOKEN = r"'[\p{L}\p{N}]+|[^\s\p{L}\p{N}]'"


def toks(column: str) -> str:
    return f"regexp_extract_all(lower({column}), {TOKEN})"


PAIRS = {
    "turns": "SELECT conv_id * 1000 + turn AS sample_id, role, coalesce(text, '') AS text, lead(role) OVER w AS next_role, lead(text) OVER w AS next_text FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)",
    "pairs": "SELECT sample_id, text AS instruction, next_text AS response FROM turns WHERE role = 'user' AND next_role = 'assistant' AND length(trim(coalesce(next_text, ''))) > 0",
    "tp": f"SELECT sample_id, {toks('instruction')} AS instr, {toks('response')} AS resp FROM pairs",
}
DOC_PAIRS = {
    "dt": f"SELECT doc_id AS sample_id, {toks('text')} AS t FROM documents",
    "dp": "SELECT sample_id, list_slice(t, 1, least(32, len(t) // 4)) AS instr, list_slice(t, least(32, len(t) // 4) + 1, len(t)) AS resp FROM dt WHERE len(t) >= 8",
}
#: Needs ``tp``.
NGRAM = {
    "ct": f"SELECT {toks('text')} AS t FROM documents",
    "cu": "SELECT tok, count(*) AS n FROM (SELECT unnest(t) AS tok FROM ct) GROUP BY tok",
    "voc": "SELECT tok, n / (SELECT sum(n) FROM cu) AS pu FROM cu",
    "cb": "SELECT prev, tok, count(*) AS n FROM (SELECT unnest(list_concat(['<s>'], t[:-2])) AS prev, unnest(t) AS tok FROM ct WHERE len(t) > 0) GROUP BY prev, tok",
    "ch": "SELECT prev, sum(n) AS c FROM cb GROUP BY prev",
    "raw": "SELECT sample_id, len(instr) AS ni, unnest(generate_series(0, len(instr) + len(resp) - 1)) AS g, unnest(list_concat(instr, resp)) AS tok FROM tp",
    "known": "SELECT sample_id, ni, g, g - ni AS k, coalesce(voc.tok, '<unk>') AS w, coalesce(pu, 0) AS pu FROM raw LEFT JOIN voc ON raw.tok = voc.tok",
    "pos": """SELECT *, coalesce(lag(w) OVER (PARTITION BY sample_id ORDER BY g), '<s>') AS p, row_number() OVER (PARTITION BY sample_id, w ORDER BY g) - 1 AS seen,
  row_number() OVER (PARTITION BY sample_id, k >= 0, w ORDER BY g) - 1 AS seen_out FROM known""",
    "look": """SELECT sample_id, k, g, pu, seen, seen_out, CASE WHEN ch.prev IS NULL THEN pu ELSE coalesce(b.n, 0) / ch.c END AS fw,
  CASE WHEN k = 0 THEN coalesce(s.n, 0) / (SELECT c FROM ch WHERE prev = '<s>') WHEN ch.prev IS NULL THEN pu ELSE coalesce(b.n, 0) / ch.c END AS fo
  FROM pos LEFT JOIN cb b ON b.prev = p AND b.tok = w LEFT JOIN ch ON ch.prev = p LEFT JOIN cb s ON s.prev = '<s>' AND s.tok = w WHERE k >= 0""",
    "lp": """SELECT sample_id, (k + 1)::INTEGER AS pos,
  ln(0.4 * fw + 0.2 * pu + 0.1 / ((SELECT count(*) FROM voc) + 1) + CASE WHEN g > 0 THEN 0.3 * seen / g ELSE 0.3 * pu END) AS lp_with,
  ln(0.4 * fo + 0.2 * pu + 0.1 / ((SELECT count(*) FROM voc) + 1) + CASE WHEN k > 0 THEN 0.3 * seen_out / k ELSE 0.3 * pu END) AS lp_without FROM look""",
    "sc": "SELECT sample_id, count(*) AS n_tokens, exp(-avg(lp_with)) AS ppl_with, exp(-avg(lp_without)) AS ppl_without, exp(avg(lp_without - lp_with)) AS ifd FROM lp GROUP BY sample_id",
}
HASHED = {
    "et": "SELECT sample_id, unnest(instr) AS tok FROM tp",
    "eh": "SELECT sample_id, tok, ('0x' || substr(md5('42:' || tok), 1, 8))::BIGINT AS h FROM et",
    "ec": "SELECT sample_id, h % 64 AS b, sum(CASE WHEN (h // 64) % 2 = 0 THEN 1.0 ELSE -1.0 END * {w}) AS x FROM {eh} GROUP BY ALL",
    "ed": "SELECT tp.sample_id, d.dim, coalesce(ec.x, 0)::DOUBLE AS x FROM tp CROSS JOIN (SELECT unnest(generate_series(0, 63)) AS dim) d LEFT JOIN ec ON ec.sample_id = tp.sample_id AND ec.b = d.dim",
    "vec": "SELECT sample_id, list(CASE WHEN nn > 0 THEN x / nn ELSE x END ORDER BY dim) AS v FROM (SELECT *, sqrt(sum(x * x) OVER (PARTITION BY sample_id)) AS nn FROM ed) GROUP BY sample_id",
}
EMBED = HASHED | {"ec": HASHED["ec"].format(w="1", eh="eh")}
EMBED_TFIDF = {
    "et": HASHED["et"],
    "edf": "SELECT tok, ln((1 + (SELECT count(*) FROM tp)) / (1 + count(DISTINCT sample_id))) + 1 AS w FROM et GROUP BY tok",
    "eh": "SELECT sample_id, tok, ('0x' || substr(md5('42:' || tok), 1, 8))::BIGINT AS h, w FROM et JOIN edf USING (tok)",
    "ec": HASHED["ec"].format(w="w", eh="eh"),
    "ed": HASHED["ed"],
    "vec": HASHED["vec"],
}
GIVEN = {"vec": "SELECT vec_id AS sample_id, embedding::DOUBLE[] AS v FROM embeddings"}


def kmeans(k: int = 10, iters: int = 10, order: str = "sample_id") -> dict[str, str]:
    """Unrolled Lloyd rounds; needs ``vec``; ends in ``cl`` (sample_id, cluster_id, dist) and ``cen`` (cluster_id, c)."""
    out = {"c0": f"SELECT row_number() OVER (ORDER BY {order}) - 1 AS cluster_id, v AS c FROM vec ORDER BY {order} LIMIT {k}"}
    near = "SELECT sample_id, v, cluster_id, d FROM (SELECT sample_id, v, cluster_id, d, row_number() OVER (PARTITION BY sample_id ORDER BY d, cluster_id) AS r FROM (SELECT sample_id, v, cluster_id, list_sum(list_transform(list_zip(v, c), lambda p: (p[1] - p[2]) * (p[1] - p[2]))) AS d FROM vec CROSS JOIN c{i})) WHERE r = 1"
    for i in range(iters):
        out[f"a{i}"] = near.format(i=i)
        out[f"m{i}"] = f"SELECT cluster_id, list(x ORDER BY dim) AS c FROM (SELECT cluster_id, dim, avg(x) AS x FROM (SELECT cluster_id, unnest(v) AS x, unnest(generate_series(1, len(v))) AS dim FROM a{i}) GROUP BY ALL) GROUP BY cluster_id"
        out[f"c{i + 1}"] = f"SELECT cluster_id, coalesce(m.c, o.c) AS c FROM c{i} o LEFT JOIN m{i} m USING (cluster_id)"
    out["cl"] = f"SELECT sample_id, cluster_id::INTEGER AS cluster_id, sqrt(d) AS dist FROM ({near.format(i=iters)})"
    out["cen"] = f"SELECT cluster_id::INTEGER AS cluster_id, c FROM c{iters}"
    return out


#: Needs ``sc`` and ``cl``.
SCORED = {"scored": "SELECT sample_id, cluster_id, dist, sc.ifd FROM sc JOIN cl USING (sample_id)"}
ALL = PAIRS | NGRAM | EMBED | kmeans() | SCORED


def sql(parts: dict[str, str], final: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(f"{k} AS MATERIALIZED ({v})" for k, v in parts.items()) + "\n" + final


def ranked(order: str = "round(ifd, 9) DESC, sample_id", where: str = "true", cluster: str = "cluster_id") -> str:
    return f"SELECT sample_id, {cluster} AS cluster_id, ifd, row_number() OVER (PARTITION BY {cluster} ORDER BY {order}) AS rank, count(*) OVER (PARTITION BY {cluster}) AS n FROM scored WHERE {where}"


CHOSEN = "SELECT sample_id, cluster_id::INTEGER AS cluster_id, round(ifd, 6) AS ifd, rank FROM ({r}) WHERE rank <= {q}"


def chosen(rate: int, add: int = 99, **how: str) -> str:
    return CHOSEN.format(r=ranked(**how), q=f"(n * {rate} + {add}) // 100")


def lengths(kind: str) -> dict[str, str]:
    if kind == "pairs":
        return PAIRS | {"ln": "SELECT sample_id, (len(instr) + len(resp))::INTEGER AS n_tokens FROM tp"}
    return DOC_PAIRS | {"ln": "SELECT sample_id, (len(instr) + len(resp))::INTEGER AS n_tokens FROM dp"}


def batched(kind: str, size: int = 256) -> dict[str, str]:
    return lengths(kind) | {"ba": f"SELECT (row_number() OVER (ORDER BY sample_id) - 1) // {size} AS batch_id, sample_id, n_tokens FROM ln"}


def packed(kind: str, context: int, fit: str, direction: str = "DESC", size: int = 256, where: str = "true") -> dict[str, str]:
    """A fold over the sorted items of every batch; ends in ``pk`` (batch_id, row_id, sample_id, offset, length)."""
    spot = {
        "first": f"list_position(list_transform(s.used, lambda u: u + i.n <= {context}), true)",
        "best": f"list_position(s.used, list_max(list_filter(s.used, lambda u: u + i.n <= {context})))",
        "next": f"CASE WHEN len(s.used) > 0 AND s.used[len(s.used)] + i.n <= {context} THEN len(s.used) ELSE 0 END",
    }[fit]
    return batched(kind, size) | {
        "items": f"SELECT batch_id, sample_id, n_tokens AS n, row_number() OVER (PARTITION BY batch_id ORDER BY n_tokens {direction}, sample_id) AS rn FROM ba WHERE {where}",
        "st": f"""SELECT batch_id, 0::BIGINT AS rn, []::INTEGER[] AS used, NULL::BIGINT AS sample_id, 0 AS slot, 0 AS off, 0 AS n FROM (SELECT DISTINCT batch_id FROM items)
  UNION ALL
  SELECT batch_id, rn, CASE WHEN slot > 0 THEN list_concat(list_concat(used[:slot - 1], [used[slot] + n]), used[slot + 1:]) ELSE list_append(used, n) END,
    sample_id, CASE WHEN slot > 0 THEN slot ELSE len(used) + 1 END::INTEGER, CASE WHEN slot > 0 THEN used[slot] ELSE 0 END, n
  FROM (SELECT s.batch_id, i.rn, s.used, i.sample_id, i.n, coalesce({spot}, 0)::INTEGER AS slot FROM st s JOIN items i ON i.batch_id = s.batch_id AND i.rn = s.rn + 1)""",
        "pk": 'SELECT batch_id, (slot - 1)::INTEGER AS row_id, sample_id, off::INTEGER AS "offset", n::INTEGER AS length FROM st WHERE rn > 0',
    }


#: Measures of a layout given as a table of batches: b(rows, width, used, truncated).
MEASURES = """count(*)::BIGINT AS batches, sum(rows)::BIGINT AS rows, sum(rows * width)::BIGINT AS cells, sum(used)::BIGINT AS used, round(1 - sum(used) / sum(rows * width), 6) AS padding_rate,
  sum(rows * width * width)::BIGINT AS attention_cells, max(rows * width)::BIGINT AS peak_cells, max(rows * width * width)::BIGINT AS peak_attention, sum(truncated)::BIGINT AS truncated"""
PACKED_BATCHES = "SELECT batch_id, count(*) AS rows, max(u) AS width, sum(u) AS used, 0 AS truncated FROM (SELECT batch_id, row_id, sum(length) AS u FROM pk GROUP BY ALL) GROUP BY batch_id"
PADDED = "SELECT batch_id, count(*) AS rows, {w} AS width, sum({n}) AS used, sum(n_tokens - {n}) AS truncated FROM ba GROUP BY batch_id"
STREAMED = "SELECT batch_id, (sum(least(n_tokens, 512)) + 511) // 512 AS rows, 512 AS width, sum(least(n_tokens, 512)) AS used, sum(n_tokens - least(n_tokens, 512)) AS truncated FROM ba GROUP BY batch_id"
