"""The given fixtures in SQL that DuckDB runs: named views, put in front of a query in the order they depend on each other."""

from __future__ import annotations

from ..ontology import LABELS, RELATIONS, TYPES
from ..sources.tables import DEV_BELOW, LANG_TYPE, TRAIN_BELOW


def text(x: str) -> str:
    return "'" + x.replace("'", "''") + "'"


LABEL_LIST = "[" + ", ".join(map(text, LABELS)) + "]"


def hashed(seed, stream, *ids: str) -> str:
    parts = f"'{seed}:{stream}'" if isinstance(stream, str) and not stream.startswith("(") else f"'{seed}:' || {stream}"
    return "md5(" + " || ':' || ".join([parts, *[f"cast({i} as varchar)" for i in ids]]) + ")"


def hashed_int(seed, stream, *ids: str) -> str:
    return f"('0x' || substr({hashed(seed, stream, *ids)}, 1, 7))::BIGINT"


def block(grid: str, base: str, width: int) -> str:
    at = [f"{grid}[{base} + {d}]" for d in (1, 2, width + 1, width + 2)]
    return f"(({' + '.join(at)}) / 4)"


_PAIRS = "CASE " + " ".join(f"WHEN o = '{o}' AND e = '{e}' THEN [{', '.join(text(f'/{o}/{e}/{r}') for r in rs)}]" for o, e, rs in RELATIONS) + " END"
_SAMPLES = f"""
SELECT sample_id, vec_id, image, x0, y0, crop, text, entity, e AS ent_type, o AS obj_type,
  CASE WHEN is_real AND own IS NOT NULL THEN own[which % len(own) + 1] ELSE 'none' END AS gold,
  CASE WHEN prefix < '{TRAIN_BELOW}' THEN 'train' WHEN prefix < '{DEV_BELOW}' THEN 'dev' ELSE 'test' END AS split
FROM (SELECT *, {_PAIRS} AS own FROM (
  SELECT *, ['{"', '".join(TYPES)}'][(2 * (cp0 >= 0)::INT + (cp3 >= 0)::INT) + 1] AS o,
    {block("image", "0", 8)} + cp1 > 0.03 AS is_real,
    2 * ({block("image", "18", 8)} >= 0)::INT + ({block("image", "36", 8)} >= 0)::INT AS which
  FROM (SELECT *, {block("image", "y0 * 8 + x0", 8)} AS cp0, {block("image", "y0 * 8 + x0 + 2", 8)} AS cp1, {block("image", "y0 * 8 + x0 + 18", 8)} AS cp3,
      list_concat(list_concat(image[y0*8+x0+1 : y0*8+x0+4], image[y0*8+x0+9 : y0*8+x0+12]), list_concat(image[y0*8+x0+17 : y0*8+x0+20], image[y0*8+x0+25 : y0*8+x0+28])) AS crop
    FROM (SELECT v.vec_id, v.image, d.text, j, v.vec_id * 4 + j AS sample_id, (v.vec_id + j) % 5 AS x0, (v.vec_id // 5 + 2 * j) % 5 AS y0,
        regexp_extract(d.text, '[A-Za-z]{{4,}}', 0) AS entity, substr({hashed(42, "split", "v.vec_id")}, 1, 4) AS prefix,
        CASE d.lang {" ".join(f"WHEN '{k}' THEN '{v}'" for k, v in LANG_TYPE.items())} END AS e
      FROM (SELECT vec_id, embedding::DOUBLE[] AS image FROM embeddings) v JOIN documents d ON d.doc_id = v.vec_id, (SELECT unnest([0, 1, 2, 3]) AS j)))))"""

_PREDS = f"""
SELECT m AS method, sample_id, gold, CASE WHEN substr({hashed(7, "pred", "m", "sample_id")}, 1, 2) < cut THEN gold
  ELSE {LABEL_LIST}[{hashed_int(7, "other", "m", "sample_id")} % {len(LABELS)} + 1] END AS pred
FROM samples, (VALUES ('strong', 'd0'), ('middle', 'b0'), ('weak', '90')) AS m(m, cut) WHERE split = 'test'"""

_STEP1 = "'Step 1: ' || regexp_replace(text, '[\\n<>]', ' ', 'g') || chr(10) || 'Step 2: noted' || chr(10)"
_LOGGED = f"""
SELECT conv_id AS sample_id, turn AS k, gold, lp_old, lp_old + ((turn * 7 + conv_id) % 11 - 5) / 20.0::DOUBLE AS lp_cur, lp_old + ((turn * 3 + conv_id) % 7 - 3) / 25.0::DOUBLE AS lp_ref,
  '<think>' || {_STEP1} || CASE WHEN fault BETWEEN '20' AND '3f' THEN '' ELSE 'Step 3: noted' || chr(10) END || 'Step 4: noted' || chr(10) || 'Step 5: noted' || chr(10) || 'Step 6: noted' || chr(10) || '</think>'
    || CASE WHEN fault < '10' THEN '' ELSE '<answer>' || said || '</answer>' END AS response
FROM (SELECT *, CASE WHEN fault < '90' THEN gold ELSE other END AS said FROM (
  SELECT conv_id, turn, text, {LABEL_LIST}[{hashed_int(7, "gold", "conv_id")} % {len(LABELS)} + 1] AS gold, {LABEL_LIST}[{hashed_int(7, "pred", "conv_id", "turn")} % {len(LABELS)} + 1] AS other,
    substr({hashed(7, "fault", "conv_id", "turn")}, 1, 2) AS fault, -(length(text) % 97) / 50.0::DOUBLE - 0.5::DOUBLE AS lp_old
  FROM conversations WHERE role = 'assistant'))"""

_SPACE = "' ' || chr(9) || chr(10) || chr(13)"
_PARSED = f"""
SELECT *, array_to_string(regexp_extract_all(think, 'Step ([0-9]+):', 1), ',') AS step_order, list_transform(string_split_regex(think, 'Step [0-9]+:')[2:], lambda x: trim(x, {_SPACE})) AS steps,
  has_think AND n_answers = 1 AND regexp_full_match(response, '(?s)\\s*<think>\\s*Step 1:.*Step 2:.*Step 3:.*Step 4:.*Step 5:.*Step 6:.*</think>\\s*<answer>\\s*[^<\\s][^<]*</answer>\\s*') AND len(regexp_extract_all(think, 'Step [0-9]+:')) = 6 AS well_formed
FROM (SELECT *, len(string_split(response, '<think>')) = 2 AND len(string_split(response, '</think>')) = 2 AND regexp_matches(response, '(?s)<think>.*</think>') AS has_think,
  regexp_extract(response, '(?s)<think>(.*)</think>', 1) AS think, len(string_split(response, '<answer>')) - 1 AS n_answers, trim(regexp_extract(response, '(?s)<answer>([^<]*)</answer>', 1), {_SPACE}) AS answer FROM {{}})"""

_REWARDED = f"""
SELECT *, r_format + r_length + r_answer AS reward FROM (SELECT *,
  (well_formed AND list_contains({LABEL_LIST}, answer))::INT::DOUBLE AS r_format,
  (length(response) > 1024)::INT::DOUBLE AS r_length, (answer = gold)::INT::DOUBLE AS r_answer FROM parsed_logged)"""

_TABULAR = """
SELECT sample_id, k, answer, gold, r_format, r_length, (answer = gold)::INT::DOUBLE AS r_answer, r_format + r_length + (answer = gold)::INT::DOUBLE AS reward, lp_old, lp_old + (l_discount - 0.05::DOUBLE) * 4 AS lp_cur, lp_old + (l_tax - 0.04::DOUBLE) * 2 AS lp_ref
FROM (SELECT l_orderkey AS sample_id, l_linenumber::BIGINT AS k, l_returnflag || l_linestatus AS answer, (l_linenumber <= 5)::INT::DOUBLE AS r_format, (l_extendedprice > 30000)::INT::DOUBLE AS r_length, -l_quantity / 50 AS lp_old, l_discount, l_tax,
  CASE WHEN substr(o_orderpriority, 1, 1) <= '2' THEN 'A' WHEN substr(o_orderpriority, 1, 1) <= '3' THEN 'N' ELSE 'R' END || CASE WHEN o_orderstatus = 'P' THEN 'O' ELSE o_orderstatus END AS gold
  FROM lineitem JOIN orders ON o_orderkey = l_orderkey)"""


def advantages(source: str, ddof: int = 0) -> str:
    fn = "stddev_pop" if ddof == 0 else "stddev_samp"
    return f"SELECT *, CASE WHEN coalesce(sd, 0) <= 1e-12 THEN 0 ELSE (reward - mean) / sd END AS adv FROM (SELECT *, avg(reward) OVER (PARTITION BY sample_id) AS mean, {fn}(reward) OVER (PARTITION BY sample_id) AS sd FROM {source})"


def terms(source: str) -> str:
    return f"""SELECT *, least(ratio * adv, greatest(0.8, least(1.2, ratio)) * adv) AS clipped, exp(lp_ref - lp_cur) - (lp_ref - lp_cur) - 1 AS divergence,
      ((adv > 0 AND ratio > 1.2) OR (adv < 0 AND ratio < 0.8)) AS is_cut FROM (SELECT *, exp(lp_cur - lp_old) AS ratio FROM {source})"""


_POOLED = f"SELECT sample_id, gold, CASE WHEN substr({hashed(7, 'skill', 'sample_id')}, 1, 2) < 'ca' THEN 'easy' ELSE 'hard' END AS pool FROM cold WHERE NOT drawn"
_COLD = f"""SELECT *, row_number() OVER (PARTITION BY gold ORDER BY {hashed(42, 'cold', 'sample_id')}, sample_id) <= greatest(1, floor(0.25 * count(*) OVER (PARTITION BY gold) + 0.5)) AS drawn
FROM samples WHERE split = 'train'"""

_BRIEF = f"{text('Given a picture, a marked object in it and a text with an entity, tell how the object relates to the entity. Think between <think> and </think> and give one label between <answer> and </answer>. Labels: ' + ', '.join(LABELS) + '. Entity: ')} || coalesce(entity, '') || '. Text: ' || coalesce(text, '')"
_HINT = "CASE WHEN gold = 'none' THEN 'Hint: nothing relates the object to the entity.' ELSE 'Hint: the object is of type ' || split_part(gold, '/', 2) || ', the entity of type ' || split_part(gold, '/', 3) || ', and the relation is ' || split_part(gold, '/', 4) || '.' END"
_ANNOTATED = f"""
SELECT sample_id, gold, CASE WHEN f < '08' THEN '' ELSE '<think>' || s1 || 'Step 2: related ' || related || chr(10) || CASE WHEN f < '10' THEN '' ELSE 'Step 3: matched' || chr(10) END || 'Step 4: types ' || obj_type || ' and ' || coalesce(ent_type, 'unknown') || chr(10) || 'Step 5: narrowed' || chr(10) || 'Step 6: decided' || chr(10) || '</think>' END
  || CASE WHEN f >= '10' AND f < '14' THEN '' ELSE '<answer>' || CASE WHEN f >= '14' AND f < '18' THEN 'no/such' WHEN f >= '18' AND f < '20' THEN wrong ELSE gold END || '</answer>' END AS response
FROM (SELECT *, substr({hashed(9, 'expert', 'sample_id')}, 1, 2) AS f, 'Step 1: a picture with an object and ' || entity || repeat(' It is looked at from edge to edge and in its parts before anything is said of it.', 13) || chr(10) AS s1, CASE WHEN gold = 'none' THEN 'no' ELSE 'yes' END AS related,
  CASE WHEN gold = 'none' THEN '/per/per/peer' ELSE 'none' END AS wrong FROM cold WHERE drawn)"""

VIEWS = {
    "samples": (_SAMPLES, ()),
    "preds": (_PREDS, ("samples",)),
    "metrics": (f"""SELECT method, round(a, 6) AS acc, round(coalesce(p, 0), 6) AS p, round(coalesce(r, 0), 6) AS r, round(coalesce(2 * p * r / nullif(p + r, 0), 0), 6) AS f1 FROM (
        SELECT method, avg((pred = gold)::INT::DOUBLE) AS a, sum((pred = gold AND gold <> 'none')::INT)::DOUBLE / nullif(sum((pred <> 'none')::INT), 0) AS p, sum((pred = gold AND gold <> 'none')::INT)::DOUBLE / nullif(sum((gold <> 'none')::INT), 0) AS r FROM preds GROUP BY method)""", ("preds",)),
    "logged": (_LOGGED, ()),
    "parsed_logged": (_PARSED.format("logged"), ("logged",)),
    "rewarded": (_REWARDED, ("parsed_logged",)),
    "advantaged": (advantages("rewarded"), ("rewarded",)),
    "termed": (terms("advantaged"), ("advantaged",)),
    "tabular": (_TABULAR, ()),
    "tabular_adv": (advantages("tabular"), ("tabular",)),
    "tabular_terms": (terms("tabular_adv"), ("tabular_adv",)),
    "cold": (_COLD, ("samples",)),
    "pools": (_POOLED, ("cold",)),
    "annotated": (_ANNOTATED, ("cold",)),
    "parsed_annotated": (_PARSED.format("annotated"), ("annotated",)),
    "reasoned": (f"""SELECT *, CASE WHEN NOT has_think THEN 'no_think' WHEN step_order <> '1,2,3,4,5,6' THEN 'bad_steps' WHEN answer = '' THEN 'no_answer' WHEN NOT well_formed THEN 'bad_layout' WHEN NOT list_contains({LABEL_LIST}, answer) THEN 'unknown_label' WHEN answer <> gold THEN 'wrong_answer' ELSE 'ok' END AS reason FROM parsed_annotated""", ("parsed_annotated",)),
    "ontology": ("SELECT * FROM (VALUES " + ", ".join(f"('/{o}/{e}/{r}', '{o}', '{e}', '{r}', {k})" for k, (o, e, r) in enumerate((o, e, r) for o, e, rs in RELATIONS for r in rs)) + ", ('none', NULL, NULL, 'none', 20)) AS t(label, obj_type, ent_type, relation, seq)", ()),
}
_SIX = ("Describe the picture as a whole and the marked object.", "Judge whether the text and the object have to do with each other.", "Match what the text says with what the picture shows.", "Name the type of the object and the type of the entity.", "List the relations that these two types allow.", "Choose one relation from the list, or none.")
_GUIDE = "'Go through these steps. ' || " + " || ' ' || ".join(f"'Step {k + 1}: ' || {text(x)}" for k, x in enumerate(_SIX))
BRIEF, HINT, GUIDE = _BRIEF, _HINT, _GUIDE


def using(*views: str, query: str) -> str:
    """The query with the views that it names, and what they depend on, before it."""
    order: list[str] = []

    def add(name: str) -> None:
        for d in VIEWS[name][1]:
            add(d)
        if name not in order:
            order.append(name)

    for v in views:
        add(v)
    return ("WITH " + ",\n".join(f"{n} AS MATERIALIZED ({VIEWS[n][0]})" for n in order) + "\n" if order else "") + query
