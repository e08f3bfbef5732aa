"""DuckDB SQL for the operators that SQL can express in full."""

from __future__ import annotations

from .divergence import BINS, CLASS_LIMIT, LEAST_CHARS, LEAST_SHARE, LEAST_TOTAL, LEAST_WORDS, SYMBOLS, WORD_LIMIT
from .urlfilter import HELD, ORDER, RULES
from .urlfilter import SYMBOLS as ALPHABET


def url_verdicts() -> str:
    """Rules and the character models of ``urlfilter``."""
    cases = []
    for r in sorted(RULES, key=lambda r: -len(r.text)):
        fits = f"(host = '{r.host}' OR ends_with(host, '.{r.host}')) AND starts_with(path, '{r.path}')"
        cases.append((fits, r))
    rule = " ".join(f"WHEN {f} THEN '{r.text}'" for f, r in cases)
    allow = " ".join(f"WHEN {f} THEN {str(r.allow).upper()}" for f, r in cases)
    ctes = [
        r"parsed AS (SELECT page_id, translate(regexp_extract(u, '(?s)^.*?://([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(u, '(?s)^.*?://([^/?#]*)([^?#]*)', 2) AS path, regexp_replace(regexp_replace(lower(regexp_extract(u, '(?s)^.*?://(.*)$', 1)), '[0-9]', '0', 'g'), '[^a-z0._/-]', '?', 'g') AS body FROM (SELECT page_id, coalesce(url, '') AS u FROM pages))",
        f"ruled AS (SELECT *, CASE {rule} END AS rule, CASE {allow} END AS allow FROM parsed)",
        f"units AS (SELECT body, count(*) FILTER (WHERE allow) AS acc, count(*) FILTER (WHERE NOT allow) AS rej, ('0x' || substr(md5(body), 1, 4))::INT % {HELD} = 0 AS held FROM ruled WHERE body <> '' GROUP BY body)",
        f"runs AS (SELECT body, acc, rej, held, unnest(list_transform(range(1, length(body) + 1), lambda i: substr('{'^' * (ORDER - 1)}' || body, i, {ORDER}))) AS gram FROM units)",
        "counts AS (SELECT gram, sum(CASE WHEN held THEN 0 ELSE acc END) AS a, sum(CASE WHEN held THEN 0 ELSE rej END) AS r FROM runs GROUP BY gram)",
    ]
    for k in range(1, ORDER + 1):
        lower = f"JOIN p{k - 1} ON p{k - 1}.g = substr(l.g, 2, {k - 1})" if k > 1 else ""
        qa, qr = (f"p{k - 1}.pa", f"p{k - 1}.pr") if k > 1 else (f"{1 / ALPHABET}e0", f"{1 / ALPHABET}e0")
        smooth = lambda n, q: f"CASE WHEN c.n{n} > 0 THEN (l.{n} + c.t{n} * {q}) / (c.n{n} + c.t{n})::DOUBLE ELSE {q} END AS p{n}"
        ctes += [
            f"l{k} AS (SELECT substr(gram, {ORDER + 1 - k}, {k}) AS g, sum(a)::DOUBLE AS a, sum(r)::DOUBLE AS r FROM counts GROUP BY ALL)",
            f"c{k} AS (SELECT substr(g, 1, {k - 1}) AS c, sum(a) AS na, sum(r) AS nr, count(*) FILTER (WHERE a > 0) AS ta, count(*) FILTER (WHERE r > 0) AS tr FROM l{k} GROUP BY ALL)",
            f"p{k} AS (SELECT l.g, {smooth('a', qa)}, {smooth('r', qr)} FROM l{k} l JOIN c{k} c ON c.c = substr(l.g, 1, {k - 1}) {lower})",
        ]
    of = lambda n: f"(sum({n} * score) / sum({n}))"
    spread = lambda n: f"sqrt(greatest(1e-6, sum({n} * score * score) / sum({n}) - {of(n)} * {of(n)}))"
    ctes += [
        f"scores AS (SELECT body, any_value(acc) AS acc, any_value(rej) AS rej, any_value(held) AS held, avg(ln(pa) - ln(pr)) AS score FROM runs JOIN p{ORDER} ON g = gram GROUP BY body)",
        *(f"least_{name} AS (SELECT CASE WHEN sum(acc) > 0 AND sum(rej) > 0 THEN ({of('acc')} * {spread('rej')} + {of('rej')} * {spread('acc')}) / ({spread('acc')} + {spread('rej')}) END AS t FROM scores {where})" for name, where in (("held", "WHERE held"), ("all", ""))),
        "least AS (SELECT coalesce((SELECT t FROM least_held), (SELECT t FROM least_all)) AS t)",
    ]
    return f"WITH {', '.join(ctes)} SELECT page_id, ruled.host, ruled.path, rule, CASE WHEN allow THEN 'allow' WHEN NOT allow THEN 'block' WHEN score < t THEN 'block' ELSE 'allow' END AS verdict FROM ruled LEFT JOIN scores ON scores.body = ruled.body CROSS JOIN least"


def quality_rules() -> str:
    """The measures, histograms and distances of ``divergence``."""
    space = r"[ \t\n\r\x0b\f]"
    quote = lambda x: x.replace("'", "''")
    symbols = SYMBOLS.decode()
    more = "@+=~^\\_{}"
    every = "".join(chr(c) for c in range(33, 127))
    classes = {
        "lower": "[^a-z]", "upper": "[^A-Z]", "digit": "[^0-9]", "space": r"[^ \t\n\r\x0b\f]",
        "punctuation": "[^" + "".join(rf"\x{ord(c):02x}" for c in every if not c.isalnum() and c not in symbols + more) + "]",
        "symbol": "[^" + "".join(rf"\x{ord(c):02x}" for c in symbols + more) + "]",
        "other": r"[\x00-\x7f]", "control": r"[^\x00-\x08\x0e-\x1f\x7f]",
    }
    count = lambda p: f"length(regexp_replace(text, '{quote(p)}', '', 'g'))"
    names = ", ".join(f"'{quote(w)}'" for w in BINS)
    trim = quote(".,;:!?\"'()|#*$%&")
    js = lambda p, q: f"sqrt(greatest(0.0, list_sum(list_transform(list_zip({p}, {q}), lambda z: CASE WHEN z[1] > 0 THEN z[1] * log2(z[1] / ((z[1] + z[2]) / 2)) ELSE 0.0 END + CASE WHEN z[2] > 0 THEN z[2] * log2(z[2] / ((z[1] + z[2]) / 2)) ELSE 0.0 END)) / 2))"
    share = lambda c: f"list_transform({c}, lambda v: v::DOUBLE / greatest(1, list_sum({c})))"
    add = lambda c, n: "[" + ", ".join(f"sum({c}[{k}])" for k in range(1, n + 1)) + "]"
    failed = f"n_words < {LEAST_TOTAL} OR 100 * n_repeat_words > 50 * n_words"
    return f"""WITH t AS (SELECT doc_id, lang, coalesce(text, '') AS text FROM documents),
w AS (SELECT *, list_filter(string_split_regex(text, '{space}+'), lambda x: x <> '') AS w FROM t),
v AS (SELECT doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS run FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM w)),
d AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, run) AS n FROM v) WHERE n > 1),
rep AS (SELECT doc_id, count(DISTINCT i + k) AS n_repeat FROM d, range(3) r(k) GROUP BY doc_id),
lines AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n_dup FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM t) WHERE regexp_matches(line, '[^ \\t\\n\\r\\x0b\\f]') GROUP BY doc_id),
words AS (SELECT doc_id, coalesce(list_position([{names}], lower(trim(x, '{trim}'))), {len(BINS) + 1}) AS bin, count(*) AS n FROM (SELECT doc_id, unnest(w) AS x FROM w) GROUP BY ALL),
hist AS (SELECT doc_id, list_transform(range(1, {len(BINS) + 2}), lambda k: coalesce(m[k], 0)) AS commons FROM (SELECT doc_id, map_from_entries(list((bin::BIGINT, n))) AS m FROM words GROUP BY doc_id)),
f AS (SELECT w.doc_id, w.lang, len(w) AS n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars, {count(r'[^#*$%&|<>]')} AS n_symbols, coalesce(n_dup, 0) AS n_dup_lines, coalesce(n_repeat, 0) AS n_repeat_words,
[{', '.join(count(p) for p in classes.values())}] AS classes, coalesce(commons, list_transform(range({len(BINS) + 1}), lambda k: 0)) AS commons FROM w LEFT JOIN rep USING (doc_id) LEFT JOIN lines USING (doc_id) LEFT JOIN hist USING (doc_id)),
ref AS (SELECT lang, {share('rc')} AS rc, {share('rw')} AS rw FROM (SELECT lang, {add('classes', 8)} AS rc, {add('commons', len(BINS) + 1)} AS rw FROM f WHERE lang IS NOT NULL AND NOT ({failed}) GROUP BY lang HAVING count(*) >= greatest(1, {LEAST_SHARE} * (SELECT count(*) FROM f)))),
dist AS (SELECT doc_id, bool_or((chars < {LEAST_CHARS} OR dc <= {CLASS_LIMIT}) AND (n_words < {LEAST_WORDS} OR dw <= {WORD_LIMIT})) AS near FROM (SELECT f.doc_id, n_words, list_sum(classes) AS chars, {js(share('classes'), 'rc')} AS dc, {js(share('commons'), 'rw')} AS dw FROM f, ref) GROUP BY doc_id)
SELECT doc_id, n_words::BIGINT AS n_words, word_chars, n_symbols::BIGINT AS n_symbols, n_dup_lines::BIGINT AS n_dup_lines, n_repeat_words::BIGINT AS n_repeat_words, {failed} AS base_failed, NOT ({failed}) AND coalesce(near, TRUE) AS kept FROM f LEFT JOIN dist USING (doc_id)"""
