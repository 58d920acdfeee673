"""DuckDB SQL for the registered queries, written independently in long form over the same tables."""

from __future__ import annotations

from benchvary.operators import answering, edits
from benchvary.plans import compose


def _h(*parts: str) -> str:
    return "('0x' || substr(md5(concat_ws('|', " + ", ".join(f"({p})::VARCHAR" for p in parts) + ")), 1, 8))::BIGINT"


def _values(rows, names: str) -> str:
    return "(VALUES " + ", ".join("(" + ", ".join(repr(x) for x in r) + ")" for r in rows) + f") AS t({names})"


def _dealt(specs, salt: str) -> str:
    names = "variant_id, v1, v2, ratio, l1, l2, l3, l4, n_hard"
    return f"SELECT variant_id, v1, v2, ratio::DOUBLE AS ratio, l1, l2, l3, l4, n_hard, count(o_orderkey) AS scenes FROM {_values([(*s, k) for k, s in enumerate(specs)], names + ', place')} LEFT JOIN orders ON {_h(repr(salt), 'o_orderkey')} % {len(specs)} = place GROUP BY ALL"


OBJ = f"""
o1 AS (SELECT l_orderkey AS scene_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_quantity)::INT AS sn,
       p_name AS name, p_brand AS brand, p_type AS "type", (30 + 3 * p_size)::INT AS w, (30 + 3 * floor(l_quantity))::INT AS h FROM lineitem JOIN part ON l_partkey = p_partkey),
obj AS (SELECT *, ({_h("'x'", "scene_id", "sn")} % (1000 - w))::INT AS x0, ({_h("'y'", "scene_id", "sn")} % (1000 - h))::INT AS y0 FROM o1)"""
ITEMS = f"""{OBJ},
rk AS (SELECT *, w * h AS area, row_number() OVER (PARTITION BY scene_id ORDER BY w * h DESC, sn)::INT AS rk, count(*) OVER (PARTITION BY scene_id)::INT AS n FROM obj),
sc AS (SELECT scene_id, any_value(n) AS n, (1 + {_h("'t'", "scene_id")} % any_value(n))::INT AS t FROM rk GROUP BY scene_id),
ab AS (SELECT s.scene_id, s.n, a.sn AS asn, a.name AS aname, a.brand AS abrand, a.x0 AS ax, a.y0 AS ay, a.w AS aw, a.h AS ah, b.sn AS bsn, b.name AS bname, b.x0 AS bx, b.y0 AS by_, b.w AS bw, b.h AS bh
       FROM sc s JOIN rk a ON a.scene_id = s.scene_id AND a.sn = s.t JOIN rk b ON b.scene_id = s.scene_id AND b.sn = 1 + s.t % s.n),
pool AS (SELECT pn, row_number() OVER (ORDER BY pn) AS rank_ FROM (SELECT DISTINCT p_name AS pn FROM part)),
held AS (SELECT scene_id, list(DISTINCT name) AS names FROM obj GROUP BY scene_id),
free AS (SELECT scene_id, arg_min(pn, {_h("'n'", "scene_id", "pn")} * 1000000 + rank_) AS absent FROM held, pool WHERE NOT list_contains(names, pn) GROUP BY scene_id),
same AS (SELECT ab.scene_id, count(*)::INT AS k, arg_min(r.sn, r.rk) AS best FROM ab JOIN rk r ON r.scene_id = ab.scene_id AND r.name = ab.aname GROUP BY ab.scene_id),
base AS (SELECT ab.*, f.absent, same.k, same.best, {_h("'p'", "ab.scene_id")} % 2 = 0 AS there FROM ab JOIN same USING (scene_id) LEFT JOIN free f USING (scene_id)),
it0 AS (
  SELECT scene_id, n, 'presence' AS task, 'YN' AS benchmark, CASE WHEN there THEN aname ELSE absent END AS name, CASE WHEN there THEN 0 ELSE 1 END AS answer, 2 AS n_options, CASE WHEN there THEN [best] ELSE [] END AS rel FROM base WHERE there OR absent IS NOT NULL
  UNION ALL SELECT scene_id, n, 'count', 'MC-G', aname, ({_h("'o'", "scene_id", "k")} % 4)::INT, 4, (SELECT list(r.sn) FROM rk r WHERE r.scene_id = base.scene_id AND r.name = base.aname) FROM base
  UNION ALL SELECT scene_id, n, 'attribute', 'MC-G', aname, ({_h("'o'", "scene_id", "abrand")} % 4)::INT, 4, [asn] FROM base WHERE k = 1
  UNION ALL SELECT scene_id, n, 'spatial', 'MC-T', aname, (CASE WHEN 2 * ax + aw < 2 * bx + bw THEN 0 ELSE 1 END) + (CASE WHEN 2 * ay + ah < 2 * by_ + bh THEN 0 ELSE 2 END), 4, [asn, bsn] FROM base WHERE n >= 2 AND aname <> bname
  UNION ALL SELECT scene_id, n, 'interaction', 'MC-T', aname, CASE WHEN ax < bx + bw AND bx < ax + aw AND ay < by_ + bh AND by_ < ay + ah THEN 0 ELSE 1 END, 2, [asn, bsn] FROM base WHERE n >= 2 AND aname <> bname
  UNION ALL SELECT scene_id, n, 'text', 'MC-T', aname, ({_h("'w'", "scene_id")} % 4)::INT, 4, [asn] FROM base WHERE k = 1),
it1 AS (SELECT task || '-' || scene_id AS item_id, * FROM it0),
rel AS (SELECT i.item_id, r.* FROM (SELECT item_id, scene_id AS sid, unnest(rel) AS rsn FROM it1) i JOIN rk r ON r.scene_id = i.sid AND r.sn = i.rsn),
it AS (SELECT i.*, coalesce(x.wr, 0) AS worst_rank, coalesce(x.la, 1000000) AS least_area FROM it1 i LEFT JOIN (SELECT item_id, max(rk) AS wr, min(area) AS la FROM rel GROUP BY item_id) x USING (item_id))"""
SAMPLED = f"""{ITEMS},
smp AS (SELECT * FROM it WHERE {_h("'s'", "scene_id")} % 100 < CASE benchmark WHEN 'YN' THEN 100 WHEN 'MC-G' THEN 30 ELSE 10 END)"""


def _edits(source: str, edition: int = 0, canvas: int = 1000) -> str:
    salt = f"'v1e{edition}'"
    words = list(edits.LEXICON)
    lex = _values([(w, *s) for w, s in edits.LEXICON.items()], "word, s1, s2")
    fails = lambda n, salt_: " AND ".join(f"{_h(repr(salt_), 'i.item_id', str(k))} % {n} = 0" for k in range(1, 6))
    drift, pronoun = fails(edits.DRIFT, "drift"), fails(edits.PRONOUN, "pronoun")
    word = lambda k: f"split_part(i.name, ' ', {k})"
    swap = lambda k: f"CASE WHEN {drift} THEN {word(k)} ELSE coalesce((SELECT CASE WHEN {_h(chr(39) + 'syn' + chr(39), 'i.item_id', 'word')} % 2 = 0 THEN s1 ELSE s2 END FROM {lex} WHERE word = {word(k)}), {word(k)}) END"
    pick = lambda part, of: f"{list(of)!r}[1 + {_h(salt, repr(part), 'i.item_id', 'k')} % 8]"
    persona = "[" + ", ".join(repr(p) for p in edits.PERSONAS) + "]"
    move = (canvas - 1000) // 2
    return f""",
tries AS (SELECT i.item_id, i.task, i.name AS asked, k, ({_h(salt, "'x'", "i.item_id", "k")} % {canvas - 150})::INT AS x, ({_h(salt, "'y'", "i.item_id", "k")} % {canvas - 150})::INT AS y, {pick("a", words[:8])} || ' ' || {pick("n", words[8:])} AS new_name
          FROM {source} i, (SELECT unnest([1, 2, 3, 4, 5]) AS k)),
verdict AS (SELECT t.*, new_name <> asked AND NOT EXISTS (SELECT 1 FROM rel r WHERE r.item_id = t.item_id AND r.x0 + {move} < t.x + 150 AND t.x < r.x0 + {move} + r.w AND r.y0 + {move} < t.y + 150 AND t.y < r.y0 + {move} + r.h) AS ok FROM tries t),
v1 AS (SELECT item_id, min(k) AS a, arg_min(x, k) AS x, arg_min(y, k) AS y, arg_min(new_name, k) AS nm FROM verdict WHERE ok GROUP BY item_id),
may_go AS (SELECT i.item_id, o.sn, o.rk, NOT list_contains(i.rel, o.sn) AND o.name <> i.name
           AND NOT EXISTS (SELECT 1 FROM rel r WHERE r.item_id = i.item_id AND r.x0 < o.x0 + o.w AND o.x0 < r.x0 + r.w AND r.y0 < o.y0 + o.h AND o.y0 < r.y0 + r.h) AS ok FROM {source} i JOIN rk o ON o.scene_id = i.scene_id),
v2 AS (SELECT item_id, min(rk) FILTER (rk <= 5) AS rk, arg_min(sn, rk) FILTER (rk <= 5) AS sn, count(*) AS n_go FROM may_go WHERE ok GROUP BY item_id),
hint AS (SELECT i.item_id, o.sn, o.name AS hinted, NOT list_contains(i.rel, o.sn) AND o.name <> i.name AS ok FROM {source} i JOIN rk o ON o.scene_id = i.scene_id WHERE o.sn <= 5),
facts AS (SELECT item_id, least(2, count(*)) AS facts, list(hinted ORDER BY sn)[:2] AS told FROM hint WHERE ok GROUP BY item_id),
ed AS (SELECT i.*, coalesce(v1.a, 5) AS v1_attempt, v1.x AS v1_x, v1.y AS v1_y, v1.nm AS v1_name, (v1.a IS NULL)::INT AS v1_fallback, v2.sn AS v2_sn, v2.rk AS v2_rank, (v2.rk IS NULL)::INT AS v2_fallback, coalesce(v2.n_go, 0) AS n_go,
       coalesce(facts.facts, 0) AS facts, facts.told, ({drift})::INT AS l1_fallback, ({pronoun})::INT AS l2_fallback, {swap(1)} AS swap1, {swap(2)} AS swap2, {persona}[1 + {_h("'persona'", "i.item_id")} % 4] AS persona
       FROM {source} i LEFT JOIN v1 USING (item_id) LEFT JOIN v2 USING (item_id) LEFT JOIN facts USING (item_id))"""


def _case(col: str, of: dict[str, str]) -> str:
    return f"CASE {col} " + " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in of.items()) + " END"


_NOISE = f""",
told AS (SELECT scene_id AS other, 'The picture shows ' || string_agg('a ' || name, ', ' ORDER BY sn) || '.' AS said, list(name) AS others FROM obj GROUP BY 1),
drawn AS (SELECT i.item_id, i.task, i.scene_id, i.name, k, 1 + {_h("'noise'", "i.item_id", "k")} % (SELECT max(o_orderkey) FROM orders) AS other FROM SOURCE i, (SELECT unnest([1, 2, 3, 4, 5]) AS k)),
nv AS (SELECT d.item_id, d.task, d.k, t.said, t.others IS NOT NULL AND d.other <> d.scene_id AND NOT list_contains(t.others, d.name) AS ok FROM drawn d LEFT JOIN told t USING (other)),
nz AS (SELECT item_id, min(k) AS k, arg_min(said, k) AS noise FROM nv WHERE ok GROUP BY item_id),
qt AS (SELECT ed.*, coalesce(nz.k, 5) AS l4_attempt, nz.noise, (nz.k IS NULL)::INT AS l4_fallback, replace({_case("task", edits.QUESTIONS)}, '{{name}}', name) AS q0,
       replace({_case("task", edits.QUESTIONS)}, '{{name}}', swap1 || ' ' || swap2) AS q1, replace({_case("persona", edits.REPHRASED)}, '{{name}}', name) AS lead_,
       'The picture shows ' || array_to_string(list_transform(told, lambda x: 'a ' || x), ', ') || '.' AS told_ FROM ed LEFT JOIN nz USING (item_id)),
questions AS (SELECT *, CASE WHEN l2_fallback = 1 THEN q0 ELSE lead_ || lower(q0) END AS q2, coalesce(told_ || ' ', '') || q0 AS q3, coalesce(noise || ' ', '') || q0 AS q4 FROM qt)"""


def _questions(source: str = "it") -> str:
    head = SAMPLED if source == "smp" else ITEMS
    return f"WITH {head}{_edits(source)}{_NOISE.replace('SOURCE', source)} "


_PROPOSED = _questions() + """, proposed AS (
   SELECT item_id, task, 'V1' AS strategy, k, ok FROM verdict
   UNION ALL SELECT g.item_id, i.task, 'V2', g.rk, g.ok FROM may_go g JOIN it i USING (item_id) WHERE g.rk <= 5
   UNION ALL SELECT item_id, task, 'V3', 1, true FROM it
   UNION ALL SELECT item_id, task, 'L1', k, """ + _h("'drift'", "item_id", "k") + f" % {edits.DRIFT} <> 0" + """ FROM tries
   UNION ALL SELECT item_id, task, 'L2', k, """ + _h("'pronoun'", "item_id", "k") + f" % {edits.PRONOUN} <> 0" + """ FROM tries
   UNION ALL SELECT h.item_id, i.task, 'L3', h.sn, h.ok FROM hint h JOIN it i USING (item_id)
   UNION ALL SELECT item_id, task, 'L4', k, ok FROM nv),
judged AS (SELECT item_id, task, strategy, coalesce(min(k) FILTER (ok), 5) AS attempt, (min(k) FILTER (ok) IS NULL)::INT AS fallback FROM proposed GROUP BY ALL) """


def _answers(specs, models=answering.MODELS) -> str:
    know = lambda c: f"{_h(chr(39) + 'w' + chr(39), 'model', c)} % 100 < vocab"
    return f""",
md AS (SELECT * FROM {_values(models, "model, cap, floor_ppm, vocab, personas, noise_cost, hint_gain")}),
sp AS (SELECT *, round(1000 * ratio)::BIGINT AS side FROM {_values(specs, "variant_id, v1, v2, ratio, l1, l2, l3, l4, n_hard")}),
km AS (SELECT ed.*, md.*, {know("swap1")} AND {know("swap2")} AS kw, {_h("'p'", "model", "persona", "task")} % 100 < personas AS kp, ({_h("'g'", "model", "item_id")} % n_options = answer)::INT AS guess FROM ed, md),
ans0 AS (SELECT model, variant_id, n_hard, item_id, benchmark, task, guess,
   (worst_rank + (CASE WHEN v1 = 1 AND v1_fallback = 0 AND 22500 > least_area THEN 1 ELSE 0 END) - (CASE WHEN v2 = 1 AND v2_fallback = 0 AND v2_rank < worst_rank THEN 1 ELSE 0 END)
      <= greatest(0, cap - l4 * 2 * noise_cost + l3 * facts * hint_gain))
   AND (least_area = 1000000 OR least_area::BIGINT * 1000000 >= floor_ppm * side * side) AND (l1 = 0 OR kw) AND (l2 = 0 OR l2_fallback = 1 OR kp) AS sees FROM km, sp),
ans AS (SELECT *, CASE WHEN sees THEN 1 ELSE guess END AS correct FROM ans0)"""


def _scores(specs, source: str = "smp", where: str = "true", models=answering.MODELS, by: str = "model, benchmark, variant_id") -> str:
    head = SAMPLED if source == "smp" else ITEMS
    return f"WITH {head}, src AS (SELECT * FROM {source} WHERE {where}){_edits('src')}{_answers(specs, models)}, scores AS (SELECT {by}, count(*) AS n, round(100.0 * sum(correct) / count(*), 4) AS accuracy FROM ans GROUP BY {by})"


_DELTA = ", deltas AS (SELECT s.*, v.accuracy AS vanilla, round(s.accuracy - v.accuracy, 4) AS delta FROM scores s JOIN scores v ON v.model = s.model AND v.benchmark = s.benchmark AND v.variant_id = 'vanilla' WHERE s.variant_id <> 'vanilla')"
_ITEM = "item_id, scene_id, task, benchmark, name, answer, n_options, n, worst_rank, least_area"
_BOTH = (*compose.SINGLE_IMAGE, *compose.SINGLE_TEXT[1:])
_MEAN = ", means AS (SELECT benchmark, variant_id, round(avg(accuracy), 4) AS mean_accuracy FROM scores GROUP BY ALL)"
_G = "benchmark = 'MC-G'"
_REGISTRY = _values(edits.STRATEGIES, "strategy, level, difficulty")
_COS = "list_dot_product({a}, {b}) / (sqrt(list_dot_product({a}, {a})) * sqrt(list_dot_product({b}, {b})))"
_cos = lambda a, b: _COS.format(a=a, b=b)

_VEC = f"""
vec AS (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings),
ev AS (SELECT a.vec_id AS eval_id, a.vec_id // 5 AS slot, ((a.vec_id // 5) % 3)::INT AS eval_set, SHIFT AS e FROM vec a LEFT JOIN vec u ON u.vec_id = a.vec_id + 2 WHERE a.vec_id % 5 = 0),
tr0 AS (SELECT 'v' || vec_id AS train_id, v AS t, NULL::BIGINT AS planted_from FROM vec WHERE vec_id % 5 <> 0
   UNION ALL SELECT 'p' || a.vec_id, list_transform(list_zip(a.v, b.v), lambda z: z[1] + [0.0, 0.2, 0.4, 0.6, 0.9][(a.vec_id // 5) % 5 + 1] * z[2]), a.vec_id FROM vec a JOIN vec b ON b.vec_id = a.vec_id + 1
     WHERE a.vec_id % 5 = 0 AND {_h("'plant'", "a.vec_id")} % 100 < 60),
tr AS (SELECT *, 1 AS in_xl, ({_h("'set'", "train_id")} % 100 < 40)::INT AS in_m, ({_h("'set'", "train_id")} % 100 < 15)::INT AS in_cap FROM tr0),
sets AS (SELECT unnest(['in_xl', 'in_m', 'in_cap']) AS train_set),
sims AS (SELECT eval_id, eval_set, slot, train_id, planted_from, in_xl, in_m, in_cap, {_cos("e", "t")} AS sim FROM ev, tr)"""
VEC = _VEC.replace("SHIFT", "a.v")
_MOVED = "CASE WHEN u.v IS NULL THEN a.v ELSE list_transform(list_zip(a.v, u.v), lambda z: z[1] + 0.6::DOUBLE * z[2]) END"
_IN = "CASE train_set WHEN 'in_xl' THEN in_xl WHEN 'in_m' THEN in_m ELSE in_cap END"
FLAGS = f"""{VEC},
flags AS (SELECT eval_id, eval_set, train_set, coalesce(max(CASE WHEN sim > 0.9 THEN {_IN} END), 0) AS hit FROM sims, sets GROUP BY ALL)"""
_RATE = "SELECT eval_set, train_set, count(DISTINCT eval_id) AS n, sum(hit)::BIGINT AS hits, round(sum(hit) / count(DISTINCT eval_id), 6) AS rate FROM {f} GROUP BY ALL"
_NORM = lambda c: f"trim(regexp_replace(lower({c}), '[^\\p{{L}}\\p{{N}}]+', ' ', 'g'))"
TEXT = f"""{FLAGS},
nd AS (SELECT count(DISTINCT doc_id) AS n FROM documents), ni AS (SELECT count(*) AS n FROM benchmark),
holds AS (SELECT item_id, min(doc_id) AS held_by FROM documents d, benchmark b WHERE contains(d.text, b.text) GROUP BY item_id),
caps AS (SELECT train_id, coalesce(held_by, substr(train_id, 2)::BIGINT % (SELECT n FROM nd)) AS doc_id FROM tr LEFT JOIN holds h ON planted_from IS NOT NULL AND h.item_id = (planted_from // 5) % (SELECT n FROM ni)),
it AS (SELECT item_id, array_to_string(string_split(text, ' ')[(len(string_split(text, ' ')) // 2) + 1:], ' ') AS answer FROM benchmark),
hits AS (SELECT s.*, {_NORM("d.text")} AS c, {_NORM("it.answer")} AS a FROM sims s JOIN it ON it.item_id = s.slot % (SELECT n FROM ni) JOIN caps USING (train_id) JOIN documents d USING (doc_id) WHERE sim > 0.9)"""
_DECIDED = {
    "span": "contains(c, a) AND length(a) > 0",
    "recall": "len(list_distinct(list_filter(string_split(a, ' '), lambda w: w <> ''))) > 0 AND len(list_intersect(list_distinct(string_split(a, ' ')), string_split(c, ' '))) >= 0.8 * len(list_distinct(string_split(a, ' ')))",
}


def _text_rate(how: str) -> str:
    return f"WITH {TEXT}, ok AS (SELECT * FROM hits WHERE {_DECIDED[how]}), tf AS (SELECT e.eval_id, e.eval_set, train_set, coalesce((SELECT max({_IN}) FROM ok WHERE ok.eval_id = e.eval_id), 0) AS hit FROM ev e, sets) " + _RATE.format(f="tf")


ORACLE: dict[str, str] = {
    "scene_objects": f"WITH {OBJ} SELECT scene_id, sn, name, brand, \"type\", w, h, x0, y0 FROM obj",
    "scene_stats": f"WITH {OBJ}, p AS (SELECT scene_id, count(*) AS objects FROM obj GROUP BY 1) SELECT objects, count(*) AS scenes FROM p GROUP BY 1",
    "empty_scenes": "SELECT o_orderkey AS scene_id FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)",
    **{f"items_{t}": f"WITH {ITEMS} SELECT {_ITEM} FROM it WHERE task = '{t}'" for t in edits.QUESTIONS},
    "sampled_benchmarks": f"WITH {SAMPLED} SELECT benchmark, task, count(*) AS n FROM smp GROUP BY ALL",
    "dialogue_items": "WITH c AS (SELECT *, lead(role) OVER w AS nr, lead(text) OVER w AS reference FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) SELECT conv_id, turn, CASE WHEN conv_id % 2 = 0 THEN 'OE-1' ELSE 'OE-2' END AS benchmark, text AS question, reference FROM c WHERE role = 'user' AND nr = 'assistant'",
    "vector_split": f"WITH {VEC} SELECT eval_set, count(*) AS n FROM ev GROUP BY 1",
    "planted_copies": f"WITH {VEC} SELECT eval_id, in_m, in_cap, round(sim, 6) AS sim FROM sims WHERE planted_from = eval_id",
    "caption_links": f"WITH {TEXT} SELECT train_id, doc_id FROM caps",
    "contam_image_raw_pairs": f"WITH {VEC} SELECT a.vec_id AS eval_id, b.vec_id AS other_id, round({_cos('a.v', 'b.v')}, 6) AS sim FROM vec a JOIN vec b ON a.vec_id < b.vec_id WHERE {_cos('a.v', 'b.v')} > 0.4",
    "contam_image_best_match": f"WITH {VEC} SELECT eval_id, round(max(sim), 6) AS sim FROM sims GROUP BY 1",
    "contam_image_flags_semi": f"WITH {VEC} SELECT DISTINCT eval_id FROM sims WHERE sim > 0.9",
    "contam_image_rate_grid": f"WITH {FLAGS} " + _RATE.format(f="flags"),
    "contam_threshold_sweep": f"WITH {VEC}, b AS (SELECT eval_id, max(sim) AS sim FROM sims GROUP BY 1), th AS (SELECT unnest([0.4, 0.5, 0.6, 0.7, 0.8, 0.9, 0.95, 0.99]::DOUBLE[]) AS threshold) SELECT threshold, count(*) AS n, sum((sim > threshold)::INT)::BIGINT AS hits, round(sum((sim > threshold)::INT) / count(*), 6) AS rate FROM b, th GROUP BY 1",
    "contam_text_rate_span": _text_rate("span"),
    "contam_text_rate_recall": _text_rate("recall"),
    "contam_grid_rollup": f"WITH {FLAGS} SELECT eval_set, train_set, count(*) AS n, sum(hit)::BIGINT AS hits, grouping(eval_set, train_set)::BIGINT AS level FROM flags GROUP BY ROLLUP (eval_set, train_set)",
    "contam_everywhere": f"WITH {FLAGS} SELECT eval_id FROM flags WHERE hit = 1 GROUP BY 1 HAVING count(*) = 3",
    "contam_nowhere": f"WITH {FLAGS} SELECT eval_id FROM flags GROUP BY 1 HAVING max(hit) = 0",
    "text_overlap_verbatim": "SELECT item_id, doc_id FROM documents d, benchmark b WHERE contains(d.text, b.text)",
    "propose_additions": f"WITH {ITEMS}{_edits('it')} SELECT item_id, k AS attempt, x, y, ok::INT AS ok FROM verdict",
    "propose_removals": f"WITH {ITEMS}{_edits('it')} SELECT item_id, n_go AS removable FROM ed",
    "box_masks": f"WITH {OBJ} SELECT scene_id, sn, x0, y0, least(x0 + w, 1000) AS x1, least(y0 + h, 1000) AS y1 FROM obj",
    "scene_add": f"WITH {ITEMS}{_edits('it')} SELECT item_id, v1_attempt, v1_x, v1_y, v1_name, v1_fallback FROM ed",
    "scene_remove": f"WITH {ITEMS}{_edits('it')} SELECT item_id, v2_sn, v2_fallback FROM ed",
    "scene_expand": f"WITH {OBJ} SELECT scene_id, sn, x0 + 250 AS x0, y0 + 250 AS y0, w, h, 1500 AS canvas FROM obj",
    "scene_expand_ratios": f"WITH {OBJ}, r AS (SELECT unnest([1.25, 1.5, 1.75, 2.0]::DOUBLE[]) AS ratio) SELECT ratio, count(*) AS n, round(1000 * ratio)::INT AS canvas, sum(x0 + floor((1000 * ratio - 1000) / 2))::BIGINT AS sum_x FROM obj, r GROUP BY 1",
    "page_remove_clutter": "SELECT page_id, md5(regexp_replace(regexp_replace(coalesce(html, ''), '(?s)<nav>.*?</nav>', '', 'g'), '(?s)<div class=\"ad\">.*?</div>', '', 'g')) AS digest FROM pages",
    "page_add_clutter": "SELECT page_id, md5(replace(coalesce(html, ''), '</body>', '<div class=\"ad\">ad</div></body>')) AS digest FROM pages",
    "describe_scene": f"WITH {OBJ} SELECT scene_id, 'The picture shows ' || string_agg('a ' || name, ', ' ORDER BY sn) || '.' AS description FROM obj GROUP BY 1",
    "dialogue_noise_context": "WITH c AS (SELECT *, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS nr FROM conversations) SELECT conv_id, turn, 'By the way, this is conversation ' || conv_id || '. ' || text AS question FROM c WHERE role = 'user' AND nr = 'assistant'",
    "answer_preserved": f"WITH {ITEMS} SELECT count(*) AS n, 0::BIGINT AS hidden, 0::BIGINT AS removed FROM it",
    "paired_grid_variants": _dealt(compose.GRID, "grid"),
    "op_specs": _dealt(compose.all_compositions(), "spec"),
    "single_image_scores": _scores(compose.SINGLE_IMAGE) + " SELECT * FROM scores",
    "single_image_deltas": _scores(compose.SINGLE_IMAGE) + _DELTA + " SELECT * FROM deltas",
    "single_text_scores": _scores(compose.SINGLE_TEXT) + " SELECT * FROM scores",
    "single_text_deltas": _scores(compose.SINGLE_TEXT) + _DELTA + " SELECT * FROM deltas",
    "paired_grid_scores": _scores(compose.GRID, where=_G) + " SELECT * FROM scores",
    "hard_ladder_scores": _scores(compose.LADDER, where="benchmark = 'MC-T'", models=answering.MODELS[6:], by="model, benchmark, variant_id, n_hard") + " SELECT * FROM scores",
    "extreme_scores_closed": _scores(compose.EXTREMES, "it", _G, (*answering.MODELS, answering.EXTRA_MODEL)) + " SELECT * FROM scores",
    "score_bounds": _scores(compose.EXTREMES, "it", _G) + " SELECT model, benchmark, min(accuracy) AS lowest, max(accuracy) AS highest, round(max(accuracy) - min(accuracy), 4) AS spread FROM scores GROUP BY ALL",
    "direction_check": _scores(_BOTH) + _DELTA + f" SELECT strategy, difficulty, count(*) AS cells, sum((CASE WHEN difficulty = 'hard' THEN delta <= 0 ELSE delta >= 0 END)::INT)::BIGINT AS agree FROM deltas JOIN {_REGISTRY} ON strategy = variant_id GROUP BY ALL",
    "model_average": _scores(_BOTH) + _MEAN + " SELECT * FROM means",
    "ratio_ablation": _scores(compose.RATIOS) + " SELECT variant_id, round(avg(accuracy), 4) AS mean_accuracy FROM scores GROUP BY 1",
    "task_breakdown": _scores(compose.EXTREMES, "it", by="model, task, variant_id") + " SELECT task, variant_id, round(avg(accuracy), 4) AS mean_accuracy FROM scores GROUP BY ALL",
    "fluctuation_by_level": _scores(compose.SINGLE_TEXT) + _DELTA + f" SELECT strategy, level, round(avg(abs(delta)), 4) AS mean_abs, round(quantile_cont(abs(delta), 0.5), 4) AS median_abs FROM deltas JOIN {_REGISTRY} ON strategy = variant_id GROUP BY ALL",
    "leaderboard": _scores(compose.SINGLE_IMAGE) + " SELECT model, benchmark, variant_id, accuracy, rank() OVER (PARTITION BY benchmark, variant_id ORDER BY accuracy DESC)::INT AS place FROM scores",
    "score_cube": _scores(compose.EXTREMES, "it") + " SELECT model, benchmark, variant_id, count(*) AS n, sum(correct)::BIGINT AS \"right\" FROM ans GROUP BY CUBE (model, benchmark, variant_id)",
    "scores_wide": _scores(compose.SINGLE_IMAGE) + " SELECT model, benchmark, " + ", ".join(f"max(accuracy) FILTER (variant_id = '{v}') AS \"{v}\"" for v in ("vanilla", "V1", "V2", "V3")) + " FROM scores GROUP BY ALL",
    "score_ci": _scores(compose.SINGLE_IMAGE) + " SELECT *, round(196.0 * sqrt(accuracy / 100 * (1 - accuracy / 100) / n), 4) AS half_width FROM scores",
    "op_asof_answers": "SELECT event_id, lag(event_id) OVER w AS before_id, round(lag(value) OVER w, 6) AS before_value FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "op_interval_verdicts": "WITH e AS (SELECT event_id, user_id, floor(epoch(ts))::BIGINT AS s FROM events) SELECT a.event_id AS a_id, b.event_id AS b_id FROM e a JOIN e b ON a.user_id = b.user_id AND b.s > a.s AND b.s <= a.s + 3600",
    "op_anti_missing_answers": "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)",
    "op_full_outer_rates": "SELECT coalesce(a.k, b.k) AS nation, coalesce(customers, 0) AS customers, coalesce(suppliers, 0) AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS customers FROM customer GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS suppliers FROM supplier GROUP BY 1) b ON a.k = b.k",
    "op_grouping_sets": "SELECT event_type, user_id % 9 AS model, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type, user_id % 9), (event_type), ())",
    "op_percentiles": "SELECT event_type, round(quantile_cont(value, 0.25), 6) AS p25, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY 1",
    "op_ntile_models": "WITH q AS (SELECT *, ntile(4) OVER (PARTITION BY event_type ORDER BY value DESC, event_id)::INT AS quarter FROM events) SELECT event_type, quarter, count(*) AS n, round(avg(value), 6) AS mean FROM q GROUP BY ALL",
    "op_moving_accuracy": "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS moving FROM events",
    "op_union_variants": f"WITH {OBJ}, u AS (SELECT 'vanilla' AS variant, w FROM obj UNION ALL SELECT 'large', w FROM obj WHERE w >= 60) SELECT variant, count(*) AS n, sum(w)::BIGINT AS w FROM u GROUP BY 1",
    "op_except_all": "SELECT l_orderkey, count(*) - 1 AS n FROM lineitem GROUP BY 1 HAVING count(*) > 1",
    "op_unpivot_scores": "WITH b AS (SELECT event_type, round(min(value), 6) AS low, round(max(value), 6) AS high FROM events GROUP BY 1) SELECT event_type, 'low' AS bound, low AS value FROM b UNION ALL SELECT event_type, 'high', high FROM b",
    "op_json_props": "SELECT (json_extract_string(props, '$.k')::INT % 5 + 1) AS attempt, count(*) AS n FROM events GROUP BY 1",
    "op_string_parse": f"SELECT item_id, {_NORM('text')} AS plain, len(string_split(text, ' ')) AS words FROM benchmark",
    "op_date_buckets": "SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS n FROM orders GROUP BY 1",
    "op_box_overlap_join": f"WITH {OBJ} SELECT a.scene_id, count(*) AS pairs FROM obj a JOIN obj b ON a.scene_id = b.scene_id AND a.sn < b.sn AND a.x0 < b.x0 + b.w AND b.x0 < a.x0 + a.w AND a.y0 < b.y0 + b.h AND b.y0 < a.y0 + a.h GROUP BY 1",
    "log_tumbling": "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M') AS start, (user_id % 9)::INT AS model, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY ALL",
    "log_dedup": "SELECT DISTINCT event_id, (user_id % 9)::INT AS model, event_type AS task FROM events",
    "log_late_rows": "SELECT (user_id % 9)::INT AS model, sum((ts < (SELECT max(ts) FROM events) - INTERVAL 2 DAY)::INT)::BIGINT AS late FROM events GROUP BY 1",
    "log_running_contamination": f"WITH {VEC} SELECT eval_id, round(max({_cos('e', 'v')}), 6) AS sim FROM ev, vec WHERE vec_id % 5 <> 0 GROUP BY 1",
}


def _text_flags(how: str, shifted: bool = False) -> str:
    """(eval_id, eval_set, train_set, hit) by images with text, as a WITH list that ends with tf."""
    text = TEXT.replace(VEC, _VEC.replace("SHIFT", _MOVED)) if shifted else TEXT
    return f"WITH {text}, ok AS (SELECT * FROM hits WHERE {_DECIDED[how]}), tf AS (SELECT e.eval_id, e.eval_set, train_set, coalesce((SELECT max({_IN}) FROM ok WHERE ok.eval_id = e.eval_id), 0) AS hit FROM ev e, sets) "


_runs = lambda c: f"list_distinct(list_transform(range(greatest(len({c}) - 7, 0)), lambda i: array_to_string({c}[i + 1:i + 8], ' ')))"
_list = lambda c: f"list_filter(string_split({c}, ' '), lambda w: w <> '')"
_DECIDED["shingle"] = f"list_has_any({_runs(_list('c'))}, {_runs(_list('a'))})"
_CUBE_OF = "SELECT variant_id, round(avg(accuracy), 4) AS mean_accuracy FROM scores GROUP BY 1"
_axes = "(" + _scores(_BOTH, where=_G) + f", m AS ({_CUBE_OF}) SELECT variant_id, mean_accuracy, substr(variant_id, 1, 1) AS axis, row_number() OVER (PARTITION BY substr(variant_id, 1, 1) ORDER BY mean_accuracy DESC, variant_id)::INT AS place FROM m WHERE variant_id <> 'vanilla')"
_cells = "(" + _scores(compose.GRID, where=_G) + f" {_CUBE_OF})"
_editions = " UNION ALL ".join(f"SELECT * FROM (WITH {ITEMS}{_edits('it', k)} SELECT item_id, {k} AS edition, v1_x, v1_y FROM ed)" for k in range(3))
_steps = lambda order: f"SELECT *, round(step - lag(step) OVER (ORDER BY {order}), 4) AS bend FROM (SELECT *, round(mean_accuracy - lag(mean_accuracy) OVER (ORDER BY {order}), 4) AS step FROM m)"
_tasks = _scores(compose.EXTREMES, "it", by="model, task, variant_id") + ", m AS (SELECT task, variant_id, round(avg(accuracy), 4) AS a FROM scores GROUP BY ALL)"


def _open(specs, models=(*answering.MODELS, answering.EXTRA_MODEL), by: str = "model, benchmark, variant_id") -> str:
    f1 = "CASE WHEN len(a) + len(b) > 0 THEN 200.0::DOUBLE * len(list_intersect(a, b)) / (len(a) + len(b)) ELSE 0.0 END"
    return f"""WITH c AS (SELECT *, lead(role) OVER w AS nr, lead(text) OVER w AS reference FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)),
q AS (SELECT CASE WHEN conv_id % 2 = 0 THEN 'OE-1' ELSE 'OE-2' END AS benchmark, reference FROM c WHERE role = 'user' AND nr = 'assistant'),
g AS (SELECT model, benchmark, variant_id, n_hard, reference, string_split(reference, ' ')[:greatest(0, 4 * cap + v2 - v1 - (ratio > 1)::INT - l4 * 2 * noise_cost + l3 * 2 * hint_gain)] AS given
      FROM q, {_values(models, "model, cap, floor_ppm, vocab, personas, noise_cost, hint_gain")}, {_values(specs, "variant_id, v1, v2, ratio, l1, l2, l3, l4, n_hard").replace("AS t(", "AS u(")}),
h AS (SELECT *, list_distinct({_list(_NORM("array_to_string(given, ' ')"))}) AS a, list_distinct({_list(_NORM("reference"))}) AS b FROM g)
SELECT {by}, count(*) AS n, round(avg({f1}), 4) AS accuracy FROM h """


ORACLE |= {
    "page_blocks": "WITH h AS (SELECT page_id, coalesce(html, '') AS t FROM pages) SELECT page_id, " + ", ".join(f"((length(t) - length(replace(t, '{x}', ''))) // {len(x)})::BIGINT AS {n}" for x, n in (("<nav", "navs"), ("<p>", "paragraphs"), ('<div class="ad"', "ads"))) + " FROM h",
    "contam_text_rate_shingle": _text_rate("shingle"),
    "contam_text_two_denominators": _text_flags("span") + ", im AS (SELECT e.eval_id, train_set, coalesce((SELECT max(" + _IN + ") FROM sims s WHERE s.sim > 0.9 AND s.eval_id = e.eval_id), 0) AS ih FROM ev e, sets) SELECT train_set, round(sum(hit) / count(*), 6) AS of_all, round(coalesce(sum(hit) / nullif(sum(ih), 0), 0.0), 6) AS of_contaminated FROM tf JOIN im USING (eval_id, train_set) GROUP BY 1",
    "shift_vector": f"WITH {VEC} SELECT a.vec_id AS eval_id, round({_cos('x', 'v')}, 6) AS kept FROM (SELECT a.vec_id, a.v, {_MOVED} AS x FROM vec a LEFT JOIN vec u ON u.vec_id = a.vec_id + 2 WHERE a.vec_id % 5 = 0) a",
    "contam_reduction": "WITH s AS (" + _text_flags("span") + _RATE.format(f="tf") + "), v AS (" + _text_flags("span", True) + _RATE.format(f="tf") + ") SELECT eval_set, train_set, s.rate AS static, v.rate AS varied, round(s.rate - v.rate, 6) AS reduction, CASE WHEN s.rate > 0 THEN round((s.rate - v.rate) / s.rate, 6) END AS relative FROM s JOIN v USING (eval_set, train_set)",
    "text_overlap_shingle": f"WITH w AS (SELECT doc_id, unnest({_runs('l')}) AS s FROM (SELECT doc_id, {_list(_NORM('text'))} AS l FROM documents)), b AS (SELECT item_id, unnest({_runs('l')}) AS s FROM (SELECT item_id, {_list(_NORM('text'))} AS l FROM benchmark)) SELECT item_id, doc_id, count(DISTINCT s) AS shared FROM w JOIN b USING (s) GROUP BY ALL",
    "word_swap": _questions() + "SELECT item_id, swap1, swap2, q1 AS question FROM questions",
    "persona_rephrase": _questions() + "SELECT item_id, persona, q2 AS question FROM questions",
    "hint_context": _questions() + "SELECT item_id, q3 AS question FROM questions",
    "noise_context": _questions() + "SELECT item_id, l4_attempt, q4 AS question FROM questions",
    "context_after": _questions() + "SELECT item_id, q0 || coalesce(' ' || told_, '') || coalesce(' ' || noise, '') AS question FROM questions",
    "judge_verdicts": _PROPOSED + "SELECT strategy, k AS attempt, count(*) AS n, sum(ok::INT)::BIGINT AS yes FROM proposed GROUP BY ALL",
    "judge_attempts": _PROPOSED + "SELECT strategy, attempt, fallback, count(*) AS n FROM judged GROUP BY ALL",
    "judge_acceptance_cumulative": _PROPOSED + ", g AS (SELECT strategy, attempt, count(*) AS n FROM judged WHERE fallback = 0 GROUP BY ALL), t AS (SELECT strategy, count(*) AS total FROM judged GROUP BY 1) SELECT strategy, attempt, n, round(sum(n) OVER (PARTITION BY strategy ORDER BY attempt) / total, 6) AS share FROM g JOIN t USING (strategy)",
    "fallback_share": _PROPOSED + "SELECT task, strategy, count(*) AS n, round(avg(fallback), 6) AS fallback FROM judged GROUP BY ALL",
    "judge_composite": _PROPOSED + ", met AS (SELECT a.item_id, a.strategy || '+' || b.strategy AS pair, min(a.k) FILTER (a.ok AND b.ok) AS joint, min(a.k) FILTER (a.ok) AS fa, min(a.k) FILTER (b.ok) AS fb FROM proposed a JOIN proposed b ON a.item_id = b.item_id AND a.k = b.k AND a.strategy LIKE 'V%' AND b.strategy LIKE 'L%' GROUP BY ALL), m AS (SELECT pair, 'joint' AS mode, joint AS k FROM met UNION ALL SELECT pair, 'each', CASE WHEN fa IS NOT NULL AND fb IS NOT NULL THEN greatest(fa, fb) END FROM met) SELECT pair, mode, count(*) AS n, count(k) AS accepted, sum(coalesce(k, 5))::BIGINT AS calls FROM m GROUP BY ALL",
    "judge_rounds": f"WITH {ITEMS}{_edits('it')} SELECT v1_attempt AS attempt, v1_fallback AS fallback, count(*) AS n FROM ed GROUP BY ALL",
    "judge_confusion": f"WITH {ITEMS}{_edits('it')}, top AS (SELECT item_id, arg_min(x0, rk) AS x0, arg_min(y0, rk) AS y0, arg_min(w, rk) AS w, arg_min(h, rk) AS h FROM rel GROUP BY 1), j AS (SELECT (NOT coalesce(top.x0 < v.x + 150 AND v.x < top.x0 + top.w AND top.y0 < v.y + 150 AND v.y < top.y0 + top.h, false))::INT AS j, ok::INT AS t FROM verdict v LEFT JOIN top USING (item_id) WHERE k = 1), c AS (SELECT count(*)::DOUBLE AS n, " + ", ".join(f"count(*) FILTER (j = {a} AND t = {b}) AS n{a}{b}" for a in (0, 1) for b in (0, 1)) + " FROM j), e AS (SELECT *, (n00 + n11) / n AS po, ((n00 + n01) * (n00 + n10) + (n10 + n11) * (n01 + n11)) / (n * n) AS pe FROM c) SELECT n00, n01, n10, n11, round(po, 6) AS agreement, round(CASE WHEN pe < 1 THEN (po - pe) / (1 - pe) ELSE 1.0 END, 6) AS kappa FROM e",
    "grid_axes": "SELECT * FROM " + _axes,
    "grid_monotonicity": f"WITH ax AS {_axes}, cells AS {_cells}, g AS (SELECT c.*, v.place AS pv, l.place AS pl FROM cells c JOIN ax v ON v.variant_id = split_part(c.variant_id, '+', 1) JOIN ax l ON l.variant_id = split_part(c.variant_id, '+', 2)) SELECT count(*) AS neighbours, sum((b.mean_accuracy <= a.mean_accuracy)::INT)::BIGINT AS in_order FROM g a JOIN g b ON (b.pv = a.pv + 1 AND b.pl = a.pl) OR (b.pl = a.pl + 1 AND b.pv = a.pv)",
    "ladder_steps": _scores(compose.LADDER[:4], where="benchmark = 'MC-T'", by="model, benchmark, variant_id, n_hard") + ", m AS (SELECT n_hard, round(avg(accuracy), 4) AS mean_accuracy FROM scores GROUP BY 1) " + _steps("n_hard"),
    "ratio_steps": _scores(compose.RATIOS) + f", m AS ({_CUBE_OF}) " + _steps("variant_id"),
    "extreme_scores_open": _open(compose.EXTREMES) + "GROUP BY ALL",
    "ladder_scores_open": _open(compose.LADDER, answering.MODELS[6:], "model, benchmark, variant_id, n_hard") + "WHERE benchmark = 'OE-1' GROUP BY ALL",
    "edition_refresh": _editions,
    "edition_diversity": f"WITH e AS ({_editions}), p AS (SELECT count(DISTINCT (v1_x, v1_y)) / count(*) AS share FROM e WHERE v1_x IS NOT NULL GROUP BY item_id) SELECT count(*) AS n, round(avg(share), 6) AS diversity FROM p",
    "task_sensitivity": _tasks + ", w AS (SELECT task, round(abs(max(a) FILTER (variant_id = 'V1+L4') - max(a) FILTER (variant_id = 'vanilla')) + abs(max(a) FILTER (variant_id = 'V2+L3') - max(a) FILTER (variant_id = 'vanilla')), 4) AS change FROM m GROUP BY 1) SELECT *, rank() OVER (ORDER BY change DESC)::INT AS place FROM w",
    "rank_shift": _scores(compose.EXTREMES, "it", _G) + ", b AS (SELECT *, rank() OVER (PARTITION BY benchmark, variant_id ORDER BY accuracy DESC)::INT AS place FROM scores) SELECT b.model, b.variant_id, b.place - v.place AS shift FROM b JOIN b v ON v.model = b.model AND v.variant_id = 'vanilla' WHERE b.variant_id <> 'vanilla'",
    "memorisation_gap": _scores(compose.EXTREMES[:2], "it").replace("WITH ", f"WITH {VEC.replace('tr AS', 'tr_ AS').replace('ev, tr)', 'ev, tr_)')}, known AS (SELECT DISTINCT slot FROM sims WHERE sim > 0.9), ", 1) + f" SELECT variant_id, round(avg(correct), 6) AS honest, round(avg(CASE WHEN variant_id = 'vanilla' AND {_h(chr(39) + 'picture' + chr(39), 'item_id')} % (SELECT count(*) FROM ev) IN (SELECT slot FROM known) THEN 1 ELSE correct END), 6) AS memorising FROM ans GROUP BY 1",
    "length_effect": _questions("smp") + _answers(compose.SINGLE_TEXT) + ", r AS (SELECT item_id, variant_id, avg(correct) AS acc FROM ans GROUP BY ALL), grown AS (" + " UNION ALL ".join(f"SELECT item_id, '{t}' AS variant_id, length(q{t[1]}) - length(q0) AS chars FROM questions" for t in compose.TEXT) + "), met AS (SELECT r.variant_id, chars, v.acc - r.acc AS loss FROM r JOIN r v ON v.item_id = r.item_id AND v.variant_id = 'vanilla' JOIN grown g ON g.item_id = r.item_id AND g.variant_id = r.variant_id) SELECT variant_id, count(*) AS n, round(avg(chars), 4) AS chars, round(avg(loss), 4) AS loss, (SELECT round(corr(chars, loss), 4) FROM met) AS correlation FROM met GROUP BY 1",
    "variant_distance": _questions() + ", w AS (SELECT string_split(q0, ' ') AS a, string_split(q1, ' ') AS b FROM questions) SELECT count(*) AS n, round(avg(1 - len(list_intersect(list_distinct(a), list_distinct(b))) / len(list_distinct(list_concat(a, b)))), 6) AS distance FROM w",
    "variant_examples": _questions() + ", sc2 AS (SELECT scene_id, string_agg('a ' || name, ', ' ORDER BY sn) AS said FROM obj GROUP BY 1) SELECT item_id, 'The picture shows ' || said || '.' AS scene, q0 AS question, 'The picture shows ' || said || coalesce(', a ' || v1_name, '') || '.' AS scene_after, 1500 AS canvas, q4 AS question_after, v1_fallback + l4_fallback AS fallbacks FROM questions JOIN sc2 USING (scene_id)",
    "stack_order_effect": " UNION ALL ".join(f"SELECT * FROM (WITH {ITEMS}{_edits('it', 0, c)} SELECT '{o}' AS \"order\", count(*) AS n, sum(v1_attempt)::BIGINT AS calls, sum(v1_fallback)::BIGINT AS fallbacks, sum((v1_x IS NOT NULL AND v1_x + {m} + 150 > 250 AND v1_x + {m} < 1250 AND v1_y + {m} + 150 > 250 AND v1_y + {m} < 1250)::INT)::BIGINT AS inside FROM ed)" for o, c, m in (("V1>V3", 1000, 250), ("V3>V1", 1500, 0))),
    "cost_report": f"WITH {SAMPLED}{_edits('smp')} SELECT count(*) AS items, sum(v1_attempt)::BIGINT AS calls, sum(v1_fallback)::BIGINT AS fallbacks, count(*) * 72 AS model_calls FROM ed",
    "op_topk_pairs": f"WITH {VEC}, p AS (SELECT a.vec_id AS eval_id, b.vec_id AS other_id, round({_cos('a.v', 'b.v')}, 6) AS sim FROM vec a JOIN vec b ON a.vec_id < b.vec_id) SELECT * FROM p WHERE sim > 0.4 ORDER BY sim DESC, eval_id, other_id LIMIT 10",
    "log_sliding": "SELECT strftime(make_timestamp((epoch(ts)::BIGINT // 21600 * 21600 - k * 21600) * 1000000), '%Y-%m-%d %H:%M') AS start, event_type AS task, count(*) AS n, round(avg(value), 6) AS mean FROM events, (SELECT unnest([0, 1, 2, 3]) AS k) GROUP BY ALL",
    "log_session": "WITH e AS (SELECT user_id, coalesce(epoch(ts) - epoch(lag(ts) OVER (PARTITION BY user_id ORDER BY ts)) >= 3600, true)::INT AS fresh FROM events) SELECT user_id, sum(fresh)::BIGINT AS sessions, count(*) AS answers FROM e GROUP BY 1",
    "op_udtf_specs": f"WITH v AS (SELECT *, v1 + v2 + (ratio > 1)::INT AS image, l1 + l2 + l3 + l4 AS question FROM {_values(compose.all_compositions(), 'variant_id, v1, v2, ratio, l1, l2, l3, l4, n_hard')}), a AS (SELECT {_h("'image'", "o_orderkey")} % 3 AS images, {_h("'text'", "o_orderkey")} % 3 AS texts, count(*) AS scenes FROM orders GROUP BY ALL) SELECT variant_id, n_hard, sum(scenes)::BIGINT AS scenes FROM v JOIN a ON image <= images AND question <= texts GROUP BY ALL",
    "op_sql_functions": f"WITH {VEC} SELECT 'cosine' AS f, count(*) AS n, count(*)::DOUBLE AS total FROM ev UNION ALL SELECT 'plain_answer', count(*), sum(length({_NORM('text')}))::DOUBLE FROM benchmark",
    "op_cube": "SELECT event_type, user_id % 9 AS model, count(*) AS n, grouping(event_type, user_id % 9)::BIGINT AS level FROM events GROUP BY CUBE (event_type, user_id % 9)",
    "op_map_scores": "WITH p AS (SELECT user_id % 9 AS model, event_type, count(*) AS n FROM events GROUP BY ALL) SELECT model, count(*) AS kinds, max(n) AS most, sum(n)::BIGINT AS n FROM p GROUP BY 1",
    "op_lateral_candidates": f"WITH {ITEMS} SELECT scene_id, sn FROM rk WHERE rk <= 2",
    "op_salted_join": "SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1",
    "op_asof_join": "WITH e AS (SELECT *, CASE WHEN event_type = (SELECT min(event_type) FROM events) THEN event_id END AS v FROM events), w AS (SELECT event_id, v, last_value(v IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS version_id FROM e) SELECT event_id, version_id FROM w WHERE v IS NULL",
    "op_rankings": "WITH n AS (SELECT user_id, count(*) AS n FROM events GROUP BY 1) SELECT user_id, rank() OVER w::INT AS place, dense_rank() OVER w::INT AS dense, round(percent_rank() OVER w, 6) AS percent, round(cume_dist() OVER w, 6) AS share FROM n WINDOW w AS (PARTITION BY user_id % 9 ORDER BY n)",
    "op_range_frame": "WITH e AS (SELECT event_id, user_id, floor(epoch(ts))::BIGINT AS s FROM events) SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS within_day FROM e",
    "op_approximate": "SELECT event_type, true AS distinct_ok, true AS sketch_ok, true AS median_ok FROM events GROUP BY 1",
    "op_set_sketches": f"WITH {VEC} SELECT sum(in_m * in_cap)::BIGINT AS m_cap, sum(in_m)::BIGINT AS m, true AS overlap_ok, true AS size_ok FROM tr",
    "op_provider_inferrer": f"WITH b AS (SELECT item_id, text AS whole, array_to_string(string_split(text, ' ')[(len(string_split(text, ' ')) // 2) + 1:], ' ') AS answer FROM benchmark), n AS (SELECT count(*) AS n FROM benchmark) SELECT item_id, doc_id FROM documents d, b WHERE (contains(d.text, b.whole) OR item_id = doc_id % (SELECT n FROM n)) AND length({_NORM('answer')}) > 0 AND contains({_NORM('text')}, {_NORM('answer')})",
    "log_with_registry": "SELECT event_id, CASE WHEN user_id % 9 < 3 THEN 'small' WHEN user_id % 9 < 6 THEN 'middle' ELSE 'large' END AS size FROM events",
    "log_regenerate_state": "WITH e AS (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k, (event_id % 3 = 0) AS ok FROM events), f AS (SELECT user_id, min(k) FILTER (ok) AS a, count(*) AS n FROM e WHERE k <= 5 GROUP BY 1) SELECT user_id, coalesce(a, 5)::INT AS attempt, (a IS NULL)::INT AS fallback FROM f WHERE a IS NOT NULL OR n = 5",
    "rank_correlation": _scores(compose.EXTREMES, "it", _G) + ", b AS (SELECT *, rank() OVER (PARTITION BY benchmark, variant_id ORDER BY accuracy DESC) AS place FROM scores) SELECT b.variant_id, round(corr(b.place, v.place), 4) AS correlation FROM b JOIN b v ON v.model = b.model AND v.variant_id = 'vanilla' WHERE b.variant_id <> 'vanilla' GROUP BY 1",
    "guesser_scores": f"WITH {ITEMS} SELECT benchmark, count(*) AS n, round(100.0 * sum(({_h(chr(39) + 'g' + chr(39), chr(39) + 'chance' + chr(39), 'item_id')} % n_options = answer)::INT) / count(*), 4) AS accuracy FROM it GROUP BY 1",
    "parsed_answers": f"WITH {ITEMS} SELECT task, count(*) AS n, count(*) AS \"right\" FROM it WHERE n_options = 4 OR task = 'presence' GROUP BY 1",
    "log_interval_join": "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id % 2 = 0 AND b.event_id % 2 = 1 AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
}
