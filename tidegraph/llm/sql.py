"""DuckDB twins of the operations that SQL can express."""

from __future__ import annotations

from tidegraph.llm import decontam, licenses

_BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _quoted(words) -> str:
    return ", ".join("'" + w.replace("'", "''") + "'" for w in words)


def repeated_phrases(window: int = 50) -> str:
    """Every window by its words; a word is covered if one of the windows over it starts in an earlier document."""
    return rf"""WITH d AS (SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM documents),
s AS (SELECT doc_id, unnest(range(1, len(w) - {window - 2})) AS i, w FROM d),
h AS (SELECT doc_id, i, md5(array_to_string(w[i:i + {window - 1}], ' ')) AS h FROM s),
f AS (SELECT h, min(doc_id) AS first FROM h GROUP BY h),
c AS (SELECT DISTINCT h.doc_id, h.i FROM h JOIN f USING (h) WHERE f.first < h.doc_id),
x AS (SELECT doc_id, unnest(range(1, len(w) + 1)) AS i, unnest(w) AS word FROM d),
m AS (SELECT x.doc_id, x.i, x.word, max(CASE WHEN c.i IS NULL THEN 0 ELSE 1 END) OVER (PARTITION BY x.doc_id ORDER BY x.i ROWS {window - 1} PRECEDING) AS gone FROM x LEFT JOIN c USING (doc_id, i)),
k AS (SELECT doc_id, sum(gone)::BIGINT AS n_removed, coalesce(string_agg(word, ' ' ORDER BY i) FILTER (WHERE gone = 0), '') AS kept FROM m GROUP BY doc_id)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(k.n_removed, 0) AS n_removed, sha256(coalesce(k.kept, '')) AS kept_sha256 FROM d LEFT JOIN k USING (doc_id)"""


def license_scan(threshold: float = 0.8) -> str:
    """Every place of the phrases, and every block against every template: a block starts at each place of a template's word."""
    low = f"translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}')"
    texts = [licenses.template_words(t) for _, own in sorted(licenses.TEMPLATES.items()) for t in own]
    labels = [label for label, own in sorted(licenses.TEMPLATES.items()) for _ in own]
    templates = ", ".join(f"({k}, '{label}', {len(set(t))}, {licenses.least_of(t, threshold)}, {licenses.span_of(t, threshold)}, [{_quoted(sorted(set(t)))}])" for k, (label, t) in enumerate(zip(labels, texts)))
    words = f"list_filter(string_split_regex({low}, '{_BETWEEN}'), lambda w: w <> '')"
    places = lambda p: "list_filter(range(1, len(w) + 1), lambda i: " + " AND ".join(f"w[i + {k}] = '{x}'" for k, x in enumerate(p)) + ")"
    named = ", ".join(f"{places(p)} AS at_{k}" for k, p in licenses.PHRASES.items())
    every = "list_concat(" * (len(licenses.PHRASES) - 1) + ", ".join([f"at_{k}" for k in licenses.PHRASES][:2]) + ")" + "".join(f", at_{k})" for k in list(licenses.PHRASES)[2:])
    base = "list_filter([" + ", ".join(f"CASE WHEN len(at_{k}) > 0 THEN '{k}' END" for k in sorted(licenses.PHRASES)) + "], lambda x: x IS NOT NULL)"
    return rf"""WITH w AS (SELECT doc_id, {words} AS w FROM documents),
p AS (SELECT doc_id, len(w)::BIGINT AS n_words, {named} FROM w),
b AS (SELECT doc_id, n_words, {every} AS places, {base} AS base FROM p),
n(k, label, size, least, span, tw) AS (VALUES {templates}), t AS (SELECT k, label, size, least, span, unnest(tw) AS x FROM n),
u AS (SELECT doc_id, unnest(w) AS x, unnest(range(len(w))) AS at FROM w),
h AS (SELECT u.doc_id, u.at, u.x, t.k, t.label, t.size, t.least, t.span FROM u JOIN t ON u.x = t.x),
m AS (SELECT doc_id, k FROM h GROUP BY doc_id, k, least HAVING count(DISTINCT x) >= least), r AS (SELECT h.* FROM h JOIN m USING (doc_id, k)),
o AS (SELECT y.doc_id, y.k, y.label, y.at, y.size, y.least, count(DISTINCT z.x) AS c FROM r y JOIN r z ON y.doc_id = z.doc_id AND y.k = z.k AND z.at BETWEEN y.at AND y.at + y.span - 1 GROUP BY ALL),
g AS (SELECT doc_id, list(DISTINCT label) AS found, max(c / size) AS best FROM o WHERE c >= least GROUP BY doc_id)
SELECT b.doc_id, b.n_words, len(b.places)::BIGINT AS n_base, list_min(b.places) - 1 AS first_word, list_max(b.places) - 1 AS last_word, array_to_string(b.base, ',') AS base_labels,
  array_to_string(list_sort(list_distinct(list_concat(b.base, coalesce(g.found, [])))), ',') AS labels, CASE WHEN len(b.places) > 0 THEN 1.0 ELSE coalesce(g.best, 0.0) END::DOUBLE AS score
FROM b LEFT JOIN g USING (doc_id)"""


def decontamination(window: int = decontam.WINDOW, least: float = 0.5) -> str:
    """Template windows and windows of plain words joined by their words, for items of any length."""
    name, unit = decontam.NAME_MARK, decontam.UNIT_MARK
    twice = lambda x, pattern, to: f"regexp_replace(regexp_replace({x}, '{pattern}', '{to}', 'g'), '{pattern}', '{to}', 'g')"
    low = "lower(" + twice(f"translate(coalesce(text, ''), '{name}{unit}', '')", r"([\p{L}0-9,;)] )([A-Z][a-z])", rf"\1{name}\2") + ")"
    plain = twice(twice(low, "([0-9])[.,]([0-9])", r"\1\2"), "(^|[^0-9a-z])([0-9]+)([a-z]{1,4})($|[^0-9a-z])", rf"\1\2 {unit}\3\4")
    words = f"list_filter(string_split_regex({plain}, '{_BETWEEN}'), lambda w: w <> '')"
    bare = lambda w: f"ltrim({w}, '{name}{unit}')"
    typed = (f"list_transform(m, lambda w: CASE WHEN regexp_full_match(w, '[0-9]+') OR w IN ({_quoted(decontam.NUMBERS)}) THEN '<number>' WHEN starts_with(w, '{unit}') OR w IN ({_quoted(decontam.UNITS)}) THEN '<unit>' "
             f"WHEN starts_with(w, '{name}') OR w IN ({_quoted(decontam.NAMES)}) OR list_contains(named, w) THEN '<name>' ELSE {bare('w')} END)")  # fmt: skip

    def windows(x: str, table: str, key: str, widths: str) -> str:
        return f"""{x}m AS (SELECT DISTINCT {key} AS id, text, {words} AS m FROM {table} WHERE {key} IS NOT NULL),
{x}n AS (SELECT id, text, m, list_transform(list_filter(m, lambda w: starts_with(w, '{name}')), lambda w: {bare('w')}) AS named FROM {x}m),
{x}t AS (SELECT id, text, list_transform(m, lambda w: {bare('w')}) AS r, {typed} AS t FROM {x}n),
{x}s AS (SELECT id, text, r, t, width, unnest(range(1, len(r) - width + 2)) AS place FROM ({widths})),
{x}k AS (SELECT id, text, len(r) - width + 1 AS total, place, array_to_string(t[place:place + width - 1], ' ') AS k, array_to_string(r[place:place + width - 1], ' ') AS raw,
  [r[place + j] for j in range(width) if t[place + j][1] = '<'] AS slots FROM {x}s),
{x}w AS (SELECT * FROM {x}k UNION ALL SELECT id, text, total, place, raw, raw, [] FROM {x}k WHERE k <> raw)"""

    return f"""WITH {windows('b', 'benchmark', 'item_id', f"SELECT *, least(len(r), {window}) AS width FROM bt WHERE text IS NOT NULL AND len(r) > 0")},
{windows('d', 'documents', 'doc_id', f"SELECT dt.*, x.width FROM dt JOIN (SELECT DISTINCT width FROM bs UNION SELECT {window}) x ON len(dt.r) >= x.width")},
m AS (SELECT d.id AS doc_id, i.id AS item_id, i.text AS item, d.place - i.place AS shift, i.place, i.total, d.raw = i.raw AS exact, list_zip(i.slots, d.slots) AS pairs FROM dw d JOIN bw i USING (k)),
u AS (SELECT doc_id, item_id, item, shift, unnest(pairs) AS p FROM m), v AS (SELECT doc_id, item_id, item, shift, count(DISTINCT p) AS a, count(DISTINCT p[1]) AS b FROM u GROUP BY ALL),
o AS (SELECT m.doc_id, m.item_id, m.item, m.place, max(m.total) AS total, max(m.exact::INT) AS exact FROM m LEFT JOIN v USING (doc_id, item_id, item, shift) WHERE m.exact OR v.a IS NULL OR v.a = v.b GROUP BY ALL),
f AS (SELECT doc_id, item_id, item, max(total)::BIGINT AS n_windows, count(*) AS n_matched, sum(exact)::BIGINT AS n_exact FROM o GROUP BY ALL)
SELECT doc_id, item_id, n_windows, n_matched, n_exact, n_matched / n_windows AS coverage FROM f WHERE n_matched >= {least} * n_windows
QUALIFY row_number() OVER (PARTITION BY doc_id, item_id ORDER BY coverage DESC, n_exact DESC, n_matched DESC) = 1"""
