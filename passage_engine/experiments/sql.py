"""DuckDB building blocks of the oracles; each is a list of CTEs without the leading WITH."""

from __future__ import annotations

from ..plans.windows import MAX_SENTENCES, MAX_TOKENS

SPLIT = r"string_split(regexp_replace({0}, '([.!?]+)[ \t\r\f\n]+', '\1' || chr(1), 'g'), chr(1))"
FULL = "list_filter(list_transform({0}, lambda x: trim(x)), lambda x: length(x) > 0)"

#: Sources of (corpus, doc_id, lang, ps): ps is the list of paragraphs.
SOURCES = {
    "F-EN": f"SELECT 'F-EN' AS corpus, doc_id, lang, {FULL.format('string_split(text, chr(10))')} AS ps FROM documents WHERE lang = 'en'",
    "F-XX": f"SELECT 'F-XX' AS corpus, doc_id, lang, {FULL.format('string_split(text, chr(10))')} AS ps FROM documents WHERE lang <> 'en'",
    "F-LEC": f"SELECT 'F-LEC' AS corpus, doc_id, lang, {FULL.format('string_split(text, chr(10))')} AS ps FROM documents WHERE len(regexp_extract_all(text, '([.!?]+)[ \\t\\r\\f\\n]')) >= 100",
    "F-INT": f"SELECT 'F-INT' AS corpus, conv_id * 1000 + turn AS doc_id, 'en' AS lang, {FULL.format('string_split(text, chr(10))')} AS ps FROM conversations",
    "F-COARSE": "SELECT 'F-COARSE' AS corpus, conv_id AS doc_id, 'en' AS lang, list(replace(text, chr(10), ' ') ORDER BY turn) AS ps FROM conversations GROUP BY conv_id",
}


def sentences(*corpora: str) -> str:
    """CTEs that end in ``sents`` (corpus, doc_id, lang, idx, text, n_tok, ends_para, n_sent)."""
    source = " UNION ALL ".join(SOURCES[c] for c in corpora)
    return f"""
src AS ({source}),
pp AS (SELECT corpus, doc_id, lang, generate_subscripts(ps, 1) AS pi, unnest(ps) AS p FROM src),
ss AS (SELECT corpus, doc_id, lang, pi, {FULL.format(SPLIT.format("p"))} AS s FROM pp),
ee AS (SELECT corpus, doc_id, lang, pi, generate_subscripts(s, 1) AS si, unnest(s) AS text, len(s) AS ns FROM ss),
sents AS (SELECT corpus, doc_id, lang, (row_number() OVER (PARTITION BY corpus, doc_id ORDER BY pi, si) - 1)::INT AS idx, text,
  len(string_split_regex(text, '[ \\t\\r\\f]+'))::INT AS n_tok, si = ns AS ends_para, (count(*) OVER (PARTITION BY corpus, doc_id))::INT AS n_sent FROM ee)"""


#: The context-free cue: positive where (length + idx) mod 7 is 0.
CUE = "(length(text) + idx) % 7 = 0"


def document_lists(positive: str = CUE) -> str:
    """CTE ``lists``: prefix sums (0 first) and positions of positives of each document of ``sents``."""
    return f"""
sums AS (SELECT *, sum(n_tok) OVER (PARTITION BY corpus, doc_id ORDER BY idx) AS upto FROM sents),
lists AS (SELECT corpus, doc_id, lang, any_value(n_sent) AS n, list_prepend(0, list(upto::BIGINT ORDER BY idx)) AS pre,
  coalesce(list(idx ORDER BY idx) FILTER (WHERE {positive}), []::INT[]) AS pos FROM sums GROUP BY corpus, doc_id, lang)"""


def window_walk(policies: str, limit: int = MAX_TOKENS, cap: int = MAX_SENTENCES) -> str:
    """CTEs ``policies`` (policy, b) and the recursive ``walk`` (policy, b, corpus, doc_id, n, first, last)."""
    last = f"greatest(least(list_count(list_filter(pre, lambda q: q <= pre[first + 1] + {limit})) - 2, first + {cap} - 1), first)"
    step = """CASE WHEN last >= n - 1 THEN n ELSE greatest(first + 1, CASE WHEN policy = 'fixed' THEN last - b + 1
      ELSE coalesce(list_max(list_filter(pos, lambda q: q >= greatest(walk0.first, last - b) AND q <= last)) + 1, last) END) END"""
    step = step.replace("walk0.first", "first")
    return f"""
policies(policy, b) AS ({policies}),
walk AS (
  SELECT policy, b, corpus, doc_id, n, pre, pos, first, {last} AS last FROM (SELECT policy, b, corpus, doc_id, n, pre, pos, 0 AS first FROM lists, policies)
  UNION ALL
  SELECT policy, b, corpus, doc_id, n, pre, pos, first, {last} AS last FROM (SELECT policy, b, corpus, doc_id, n, pre, pos, {step} AS first FROM walk) WHERE first < n)"""


def with_(*parts: str) -> str:
    return "WITH RECURSIVE " + ",".join(parts)


#: Portable hash of an expression.
def h(x: str) -> str:
    return f"('0x' || substr(md5(({x})::VARCHAR), 1, 8))::BIGINT"
