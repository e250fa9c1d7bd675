"""Parts of the checking SQL, written on their own from the definitions."""

from __future__ import annotations

from doccurate.operators.qa import EXEMPLARS, FAULTS

LANGS = ["de", "en", "es", "fr"]


def u(key: str, salt: str) -> str:
    return f"(('0x' || substr(md5('{salt}|' || ({key})::VARCHAR), 1, 8))::BIGINT / 4294967296.0)"


def norm(x: str) -> str:
    return rf"trim(regexp_replace(lower({x}), '[^\p{{L}}\p{{N}}]+', ' ', 'g'))"


def words(x: str) -> str:
    return f"list_filter(string_split({norm(x)}, ' '), lambda w: w <> '')"


def char_grams(x: str, n: int = 4) -> str:
    """Distinct windows of n characters of a normal form (already normalised x)."""
    return f"list_distinct(list_transform(range(1, length({x}) - {n} + 2), lambda i: substr({x}, i, {n})))"


def quoted(s: str) -> str:
    return "'" + s.replace("'", "''") + "'"


DOC_PAGES = f"""
folded AS (
  SELECT doc_id, lang, list_reduce(
    list_transform(string_split(coalesce(text, ''), chr(10)), lambda l: {{'done': []::VARCHAR[], 'open': l}}),
    lambda s, x: CASE WHEN s.open = '' THEN {{'done': s.done, 'open': x.open}}
      WHEN length(s.open) + 1 + length(x.open) <= 800 THEN {{'done': s.done, 'open': s.open || chr(10) || x.open}}
      ELSE {{'done': list_append(s.done, s.open), 'open': x.open}} END) AS f
  FROM documents),
doc_pages AS (
  SELECT doc_id, lang, page_no, 'documents:' || doc_id || ':' || page_no AS image_id, view_parse FROM (
    SELECT doc_id, lang, unnest(list_append(f.done, f.open)) AS view_parse, unnest(range(len(f.done) + 1)) AS page_no FROM folded)),
doc_views AS (
  SELECT *, array_to_string(list_transform(string_split(view_parse, ' '), lambda w, i:
    CASE WHEN (i - 1 + floor({u('image_id', 'noise')} * 50)::INT) % 50 = 0 THEN translate(w, 'olieas', '011345') ELSE w END), ' ') AS view_ocr
  FROM doc_pages)"""

EXEMPLAR_ROWS = "exemplars(lang, ex_no, ex_question, ex_answer) AS (VALUES " + ", ".join(
    f"({quoted(lang)}, {k}, {quoted(q)}, {quoted(a)})" for lang, some in sorted(EXEMPLARS.items()) for k, (q, a) in enumerate(some)
) + ")"


def _fault() -> str:
    low, out = 0.0, "CASE"
    for name, rate in FAULTS.items():
        out += f" WHEN {u('call', 'fault')} >= {low!r} AND {u('call', 'fault')} < {low + rate!r} THEN '{name}'"
        low += rate
    return out + " END"


def calls(target: str | None) -> str:
    """CTEs up to ``parsed``: calls, completions of the stand-in, and what the format check gives."""
    where = f"WHERE lang = '{target}'" if target else ""
    return f"""{DOC_PAGES}, {EXEMPLAR_ROWS},
views AS (SELECT image_id, doc_id, lang, 'parse' AS view, view_parse AS text FROM doc_views {where}
  UNION ALL SELECT image_id, doc_id, lang, 'ocr', view_ocr FROM doc_views {where}),
ranked AS (SELECT *, list_sort(list_transform(list_filter(list_transform(regexp_split_to_array(text, '[.!?]+[ \\n]+|\\n+'), lambda s: trim(s)),
    lambda s: len(regexp_split_to_array(s, ' +')) >= 5), lambda s, i: {{'h': md5(image_id || '|' || view || '|' || (i - 1)), 's': s}})) AS r FROM views),
planned AS (SELECT *, image_id || '|' || view || '|' || slot AS call FROM ranked, (VALUES (1), (2)) AS s(slot)),
shown AS (SELECT p.*, e.ex_question, e.ex_answer, {_fault()} AS drawn FROM planned p
  LEFT JOIN exemplars e ON e.lang = p.lang AND e.ex_no = floor({u('call', 'ex')} * 3)),
cut AS (SELECT *, regexp_split_to_array(r[CASE WHEN slot > 1 AND drawn = 'paraphrase' THEN 1 ELSE slot END].s, ' +') AS ws FROM shown),
halved AS (SELECT *, ws[1:ceil(len(ws) / 2.0)::INT] AS f, ws[ceil(len(ws) / 2.0)::INT + 1:] AS rest FROM cut),
asked AS (SELECT *, CASE drawn WHEN 'off_topic' THEN ex_question
    WHEN 'wrong_language' THEN CASE WHEN lang = 'en' THEN {quoted(EXEMPLARS['de'][0][0])} ELSE {quoted(EXEMPLARS['en'][0][0])} END
    ELSE CASE WHEN f IS NOT NULL THEN array_to_string(string_split(ex_question, ' ')[1:2], ' ') || ' ' || array_to_string(
      CASE WHEN drawn = 'paraphrase' THEN list_concat(list_concat(f[2:2], f[1:1]), f[3:]) ELSE f END, ' ') || ' ?' END END AS q FROM halved),
completed AS (SELECT *, CASE WHEN ws IS NULL OR drawn = 'malformed' THEN 'Q: ' || coalesce(q, '') WHEN drawn = 'empty' THEN 'Q: ' || chr(10) || 'A: '
    ELSE 'Q: ' || q || chr(10) || 'A: ' || array_to_string(rest, ' ') END AS completion,
    CASE WHEN ws IS NULL THEN 'malformed' ELSE drawn END AS fault FROM asked),
parsed AS (SELECT image_id, doc_id, lang, view, slot, text, call, fault, completion, image_id || '#' || view || slot AS qa_id, ok AS well_formed,
    CASE WHEN ok THEN trim(regexp_extract(completion, '^Q: ([^\\n]*)\\nA: ([^\\n]*)$', 1)) END AS question,
    CASE WHEN ok THEN trim(regexp_extract(completion, '^Q: ([^\\n]*)\\nA: ([^\\n]*)$', 2)) END AS answer
  FROM (SELECT *, regexp_full_match(completion, 'Q: [^\\n]*[^\\s][^\\n]*\\nA: [^\\n]*[^\\s][^\\n]*')
    AND len(regexp_extract_all(completion, '(^|\\n)[QA]: ')) = 2 AS ok FROM completed))"""


def split_case(key: str) -> str:
    return f"CASE WHEN {u(key, 'split')} < 0.8956 THEN 'train' WHEN {u(key, 'split')} < 0.9483 THEN 'validation' ELSE 'test' END"


def profile(source: str) -> str:
    """CTEs ``prof_counts``, ``prof_size`` and ``prof``: integer scores of words by language, from rows(lang, text)."""
    totals = ", ".join(f"coalesce(sum(n) FILTER (lang = '{x}'), 0) AS t_{x}" for x in LANGS)
    scores = ", ".join(f"round(10000 * ln((coalesce(max(n) FILTER (lang = '{x}'), 0) + 1)::DOUBLE / (any_value(t_{x}) + any_value(v))))::BIGINT AS s_{x}" for x in LANGS)
    return f"""prof_counts AS (SELECT lang, gram, count(*) AS n FROM (SELECT lang, unnest({words('text')}) AS gram FROM {source}) GROUP BY ALL HAVING count(*) >= 3),
prof_size AS (SELECT count(DISTINCT gram) AS v, {totals} FROM prof_counts),
prof AS (SELECT gram, {scores} FROM prof_counts, prof_size GROUP BY gram)"""


def detected(source: str, key: str, text: str) -> str:
    """A SELECT of key, detected."""
    sums = ", ".join(f"sum(s_{x}) AS s_{x}" for x in LANGS)
    pick = "CASE WHEN s_de IS NULL THEN NULL " + " ".join(f"WHEN s_{x} = greatest(s_de, s_en, s_es, s_fr) THEN '{x}'" for x in LANGS) + " END"
    return f"SELECT k AS {key}, {pick} AS detected FROM (SELECT d.{key} AS k, {sums} FROM {source} d LEFT JOIN (SELECT {key}, unnest({words(text)}) AS gram FROM {source}) g USING ({key}) LEFT JOIN prof USING (gram) GROUP BY d.{key})"


def cascade(target: str, mode: str = "sequential") -> str:
    """CTEs up to ``judged`` (qa_id, image_id, split, fault, reasons, kept), from ``parsed``."""
    return f"""{calls(target)}, train_docs AS (SELECT lang, text FROM documents WHERE doc_id % 2 = 0), {profile('train_docs')},
pairs AS (SELECT * FROM parsed WHERE well_formed), found AS ({detected('pairs', 'qa_id', 'question')}),
measured AS (SELECT p.*, f.detected, length(trim(text)) AS len, {norm('question')} AS nq, {norm('text')} AS nt FROM pairs p JOIN found f USING (qa_id)),
grammed AS (SELECT *, {char_grams('nq')} AS gq, {char_grams('nt')} AS gt FROM measured),
tested AS (SELECT *, list_filter([CASE WHEN len > 60 THEN NULL ELSE 'length' END,
  CASE WHEN len(gq) > 0 AND len(list_intersect(gq, gt)) / len(gq)::DOUBLE >= 0.12 THEN NULL ELSE 'overlap' END,
  CASE WHEN detected = '{target}' THEN NULL ELSE 'language' END], lambda x: x IS NOT NULL) AS r FROM grammed),
alive AS (SELECT *, list_distinct(list_filter(string_split(nq, ' '), lambda w: w <> '')) AS wq, CASE view WHEN 'parse' THEN 0 ELSE 1000 END + slot AS rk FROM tested{" WHERE len(r) = 0" if mode == "sequential" else ""}),
linked AS (SELECT a.qa_id AS a, b.qa_id AS b, b.rk FROM alive a JOIN alive b ON a.image_id = b.image_id AND b.rk <= a.rk
  AND (a.nq = b.nq OR len(list_intersect(a.wq, b.wq)) / len(list_distinct(list_concat(a.wq, b.wq)))::DOUBLE >= 0.8)),
both_ways AS (SELECT a, b FROM linked UNION SELECT b, a FROM linked), two AS (SELECT x.a, y.b FROM both_ways x JOIN both_ways y ON x.b = y.a),
four AS (SELECT DISTINCT x.a, y.b FROM two x JOIN two y ON x.b = y.a),
roots AS (SELECT f.a AS qa_id, min(v.rk) < any_value(o.rk) AS dup FROM four f JOIN alive v ON v.qa_id = f.b JOIN alive o ON o.qa_id = f.a GROUP BY f.a),
judged AS (SELECT t.qa_id, t.image_id, t.doc_id, t.question, t.answer, t.text, t.lang, {split_case('t.image_id')} AS split, t.fault,
  CASE WHEN coalesce(dup, false) THEN list_append(t.r, 'paraphrase') ELSE t.r END AS reasons, len(t.r) = 0 AND NOT coalesce(dup, false) AS kept
  FROM tested t LEFT JOIN roots USING (qa_id))"""
