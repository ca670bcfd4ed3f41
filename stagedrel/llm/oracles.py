"""SQL for the operators that SQL can express on whole tables, for DuckDB."""

from __future__ import annotations


def _level(name: str, parents: list[str], level: str, weights: dict[str, int]) -> str:
    """The budgets of one level of the mixture tree, as two views: <name>n (nodes) and <name> (given)."""
    keys = ", ".join([*parents, level])
    family = f"PARTITION BY {', '.join(parents)}" if parents else ""
    before = f"OVER ({family} ORDER BY fills, {level} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)"
    w = "CASE " + level + " " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in weights.items()) + " ELSE 1 END" if weights else "1"
    up = f"JOIN {name_of(len(parents))} USING ({', '.join(parents)})" if parents else ", budget"
    return f"""{name}n AS (SELECT *, w > 0 AND cap * (all_w - w_before) <= (given - cap_before) * w AS is_full FROM (
      SELECT *, coalesce(sum(cap) {before}, 0) AS cap_before, coalesce(sum(w) {before}, 0) AS w_before, sum(w) OVER ({family}) AS all_w FROM (
        SELECT *, CASE WHEN w = 0 THEN 'inf'::DOUBLE ELSE cap::DOUBLE / w END AS fills FROM (SELECT {keys}, cap, {w} AS w FROM (SELECT {keys}, sum(cap)::BIGINT AS cap FROM leaf GROUP BY ALL)) {up}))),
    {name} AS (SELECT {keys}, CASE WHEN w = 0 THEN 0 WHEN is_full THEN cap ELSE (given - coalesce(sum(CASE WHEN is_full THEN cap END) OVER ({family}), 0)) * w // nullif(sum(CASE WHEN is_full THEN 0 ELSE w END) OVER ({family}), 0) END::BIGINT AS given FROM {name}n)"""


def name_of(depth: int) -> str:
    return f"level{depth}"


def mixing(domains, weights, share: float = 0.6, epochs: int = 2, seed: int = 17) -> str:
    names = "[" + ", ".join(f"'{d}'" for d in domains) + "]"
    levels = ["domain", "lang", "source"]
    steps = ",\n".join(_level(name_of(k + 1), [f"k_{x}" for x in levels[:k]], f"k_{x}", weights.get(x, {})) for k, x in enumerate(levels))
    leaf = "k_domain, k_lang, k_source"
    return f"""WITH base AS (SELECT *, coalesce(domain, '(null)') AS k_domain, coalesce(lang, '(null)') AS k_lang, coalesce(source, '(null)') AS k_source FROM (
      SELECT doc_id, lang, source, {names}[nullif(regexp_extract(source, '\\d{{1,6}}'), '')::INT % {len(domains)} + 1] AS domain, len(regexp_extract_all(coalesce(text, ''), '\\S+'))::BIGINT AS n_tokens FROM documents)),
    leaf AS (SELECT {leaf}, sum(n_tokens)::BIGINT AS tokens, sum(n_tokens)::BIGINT * {epochs} AS cap FROM base GROUP BY ALL),
    budget AS (SELECT floor(coalesce(sum(tokens), 0) * {share}::DOUBLE)::BIGINT AS given FROM leaf),
    {steps},
    plan AS (SELECT {leaf}, CASE WHEN tokens > 0 THEN given // tokens ELSE 0 END AS whole, CASE WHEN tokens > 0 THEN given % tokens ELSE 0 END AS rest FROM leaf JOIN {name_of(3)} USING ({leaf})),
    dealt AS (SELECT *, coalesce(sum(n_tokens) OVER (PARTITION BY {leaf} ORDER BY md5('{seed}:' || whole || ':' || coalesce(doc_id::VARCHAR, 'null')), doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS sofar FROM base JOIN plan USING ({leaf}))
    SELECT doc_id, domain, lang, source, epoch, n_tokens FROM (SELECT doc_id, domain, lang, source, n_tokens, unnest(range(whole)) AS epoch FROM dealt UNION ALL SELECT doc_id, domain, lang, source, n_tokens, whole AS epoch FROM dealt WHERE sofar < rest)"""


WARC = """SELECT page_id, bytes AS payload_bytes, digest AS payload_digest, CASE WHEN again THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN again THEN keeper END AS refers_to
  FROM (SELECT *, bytes >= 1000 AND page_id < keeper AS again FROM (SELECT page_id, strlen(coalesce(html, ''))::BIGINT AS bytes, sha1(coalesce(html, '')) AS digest, max(page_id) OVER (PARTITION BY coalesce(html, '')) AS keeper FROM pages))"""

CHATS = """WITH t AS (SELECT *, role || chr(31) || text AS enc, row_number() OVER (PARTITION BY conv_id ORDER BY turn, role, text) AS n FROM conversations),
  pre AS (SELECT conv_id, n, string_agg(enc, chr(30)) OVER (PARTITION BY conv_id ORDER BY n) AS s, count(*) OVER (PARTITION BY conv_id) AS size FROM t),
  whole AS (SELECT min(conv_id) AS conv_id, s FROM pre WHERE n = size GROUP BY s),
  kept AS (SELECT conv_id FROM whole WHERE s NOT IN (SELECT s FROM pre WHERE n < size))
  SELECT conv_id, count(*) AS n_turns, string_agg('<|im_start|>' || replace(role, '<|im_', '< |im_') || chr(10) || replace(text, '<|im_', '< |im_') || '<|im_end|>' || chr(10), '' ORDER BY n) AS chat FROM t JOIN kept USING (conv_id) GROUP BY conv_id"""

JACCARD = """WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(lower(coalesce(text, '')), '[\\p{L}\\p{N}_]+') AS w FROM documents),
  s AS (SELECT DISTINCT doc_id, array_to_string(w[i : i + least(5, len(w)) - 1], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - least(5, len(w)) + 2)) AS i FROM w WHERE len(w) > 0)),
  n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
  c AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
  links AS MATERIALIZED (SELECT a, b FROM c JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE c >= 0.8 * (x.n + y.n - c)),
  reach AS (SELECT a, b FROM links UNION SELECT r.a, l.b FROM reach r JOIN links l ON l.a = r.b)
  SELECT doc_id, (SELECT count(*) FROM links WHERE a = doc_id) AS n_links, least(doc_id, coalesce((SELECT min(b) FROM reach WHERE a = doc_id), doc_id)) AS class_id FROM w"""


def licenses(base: dict[str, str], index, upper: str, lower: str) -> str:
    rows = []
    for t, (seq, k, at, label, posted) in enumerate(index):
        rows += [f"({t}, '{label}', {len(seq)}, {len(k)}, {i}, '{w}', {int(at <= i < at + len(k))}, {int(i in posted)})" for i, w in enumerate(seq)]
    plain = [f"('{p}', '{v}', {len(p.split())}, {i}, '{w}')" for p, v in base.items() for i, w in enumerate(p.split())]
    return f"""WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{upper}', '{lower}'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS ws FROM documents),
    tpl AS (SELECT * FROM (VALUES {", ".join(rows)}) AS x(t, label, len, klen, pos, word, iskey, posted)),
    phrase AS (SELECT * FROM (VALUES {", ".join(plain)}) AS x(p, label, len, pos, word)),
    w AS MATERIALIZED (SELECT * FROM (SELECT doc_id, unnest(ws) AS w, generate_subscripts(ws, 1) - 1 AS i FROM d) WHERE w IN (SELECT word FROM tpl UNION SELECT word FROM phrase)),
    starts AS (SELECT doc_id, tpl.t, i - pos AS s FROM w JOIN tpl ON w.w = tpl.word AND posted = 1 GROUP BY ALL HAVING count(*) >= 2),
    best AS (SELECT doc_id, label, max(m / len::DOUBLE) AS share FROM (SELECT s.doc_id, s.t, label, len, klen, s.s, count(*) AS m, sum(iskey) AS mk FROM starts s JOIN tpl USING (t) JOIN w ON w.doc_id = s.doc_id AND w.i = s.s + pos AND w.w = word GROUP BY ALL) WHERE mk = klen GROUP BY ALL),
    base AS (SELECT doc_id, label, s FROM (SELECT doc_id, p, label, len, i - pos AS s, count(*) AS m FROM w JOIN phrase ON w.w = word GROUP BY ALL) WHERE m = len),
    found AS (SELECT doc_id, count(*) AS n_base, min(s) AS first_word, max(s) AS last_word, string_agg(DISTINCT label, ',' ORDER BY label) AS base_labels FROM base GROUP BY doc_id),
    named AS (SELECT doc_id, string_agg(DISTINCT label, ',' ORDER BY label) AS labels FROM (SELECT doc_id, label FROM best UNION SELECT doc_id, label FROM base) GROUP BY doc_id)
    SELECT d.doc_id, len(ws)::BIGINT AS n_words, coalesce(n_base, 0)::BIGINT AS n_base, first_word::BIGINT AS first_word, last_word::BIGINT AS last_word, coalesce(base_labels, '') AS base_labels, coalesce(labels, '') AS labels,
      round(greatest(coalesce((SELECT max(share) FROM best b WHERE b.doc_id = d.doc_id), 0), CASE WHEN n_base > 0 THEN 0.5 ELSE 0 END), 6)::DOUBLE AS score
    FROM d LEFT JOIN found ON found.doc_id = d.doc_id LEFT JOIN named ON named.doc_id = d.doc_id"""


VECTORS = """WITH RECURSIVE e AS (SELECT vec_id, label, embedding::DOUBLE[] AS v, sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])) AS n FROM embeddings WHERE label IS NOT NULL),
  links AS MATERIALIZED (SELECT a.vec_id AS a, b.vec_id AS b FROM e a JOIN e b ON a.label = b.label AND a.vec_id <> b.vec_id AND a.n > 0 AND b.n > 0 WHERE list_dot_product(a.v, b.v) / (a.n * b.n) >= 0.93),
  reach AS (SELECT a, b FROM links UNION SELECT r.a, l.b FROM reach r JOIN links l ON l.a = r.b),
  named AS (SELECT vec_id, (SELECT count(*) FROM links WHERE a = vec_id)::BIGINT AS n_links, least(vec_id, coalesce((SELECT min(b) FROM reach WHERE a = vec_id), vec_id)) AS component_id FROM embeddings)
  SELECT vec_id, n_links, component_id, vec_id = component_id AS kept FROM named"""
