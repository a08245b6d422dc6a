"""DuckDB SQL of the counting results: plain enumeration after a split at rare terms."""

from __future__ import annotations

BARRIER, TOKEN = r"[.!?\n]+", r"[\p{L}\p{N}]+"

DOCUMENTS = "select doc_id, text from documents"
PAGES = r"""
select page_id doc_id, replace(replace(replace(replace(replace(regexp_replace(regexp_replace(regexp_replace(
  regexp_extract(html, '(?s)<article[^>]*>(.*?)</article>', 1),
  '(?s)<!--.*?-->|<(script|style|nav|aside|ul)\b.*?</(script|style|nav|aside|ul)>|<div class=.?ad.*?</div>', chr(10), 'g'),
  '(?i)</?(p|div|h[1-6]|li|ul|ol|br|section|blockquote|td|tr|table)\b[^>]*>', chr(10), 'g'),
  '<[^>]*>', '', 'g'), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&nbsp;', ' '), '&amp;', '&') as text
from pages"""
BENCHMARK = "select item_id doc_id, text from benchmark"
CONVERSATIONS = "select conv_id * 1000 + turn doc_id, text from conversations"


def sampled(percent: int) -> str:
    return f"select doc_id, text from documents where substr(md5(cast(doc_id as varchar)), 1, 2) < '{256 * percent // 100:02x}'"


def sequences(source: str = DOCUMENTS, extra: str = "") -> str:
    """CTE seqs(doc_id, seq_no, w, extra) of a text source."""
    more = f", {extra}" if extra else ""
    return rf"""
parts as (select doc_id{more}, string_split_regex(text, '{BARRIER}') p from ({source})),
cut as (select doc_id{more}, unnest(p) s, unnest(range(len(p))) seq_no from parts),
seqs as (select doc_id{more}, seq_no, regexp_extract_all(lower(s), '{TOKEN}') w from cut where len(regexp_extract_all(lower(s), '{TOKEN}')) > 0)"""


EVENT_DAYS = """
seqs as (select user_id doc_id, cast(ts as date) as day, datediff('day', date '1970-01-01', cast(ts as date)) seq_no,
                list(event_type order by ts, event_id) w
         from events where user_id is not null group by user_id, cast(ts as date))"""
EVENT_USERS = """
seqs as (select user_id doc_id, 0 seq_no, list(event_type order by ts, event_id) w from events where user_id is not null group by user_id)"""
ORDERS = """
seqs as (select o_custkey doc_id, o_orderkey seq_no, cast(year(o_orderdate) as bigint) period,
                list(p_type order by l_linenumber, l_partkey, l_suppkey, l_shipdate, p_type) w
         from lineitem join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey
         group by o_custkey, o_orderkey, o_orderdate)"""


def runs(tau: int, extra: str = "") -> str:
    """CTE runs(doc_id, seq_no, start, w, extra): stretches of terms with cf >= tau."""
    more = f", {extra}" if extra else ""
    return f"""
tok as (select doc_id, seq_no{more}, unnest(w) t, unnest(range(len(w))) i from seqs),
often as (select t from tok group by t having count(*) >= {tau}),
kept as (select *, i - row_number() over (partition by doc_id, seq_no order by i) isl from tok where t in (select t from often)),
runs as (select doc_id, seq_no{more}, min(i) as start, list(t order by i) w from kept group by doc_id, seq_no{more}, isl)"""


def grams(sigma: int, extra: str = "") -> str:
    """CTE grams(doc_id, seq_no, at, gram, n, extra): one row per occurrence. Suffixes are cut first, then their prefixes."""
    more = f", {extra}" if extra else ""
    return f"""
begun as (select doc_id, seq_no, start{more}, w, unnest(range(1, len(w) + 1)) b from runs),
suf as (select doc_id, seq_no{more}, start + b - 1 as pos, w[b:b + {sigma} - 1] s from begun),
pre as (select doc_id, seq_no, pos{more}, s, unnest(range(1, len(s) + 1)) n from suf),
grams as (select doc_id, seq_no, pos{more}, array_to_string(s[1:n], ' ') gram, n from pre)"""


def ctes(tau: int, sigma: int, seqs: str | None = None, extra: str = "") -> str:
    return f"with {seqs or sequences()}, {runs(tau, extra)}, {grams(sigma, extra)}"


def stats(tau: int, sigma: int, seqs: str | None = None) -> str:
    return f"{ctes(tau, sigma, seqs)} select gram, n, count(*) cf from grams group by gram, n having count(*) >= {tau}"


def stats_cte(tau: int, sigma: int, seqs: str | None = None, name: str = "stats") -> str:
    """The same as one more CTE."""
    return f"{ctes(tau, sigma, seqs)}, {name} as materialized (select gram, n, count(*) cf from grams group by gram, n having count(*) >= {tau})"


def condensed(tau: int, sigma: int, mode: str) -> str:
    """maximal, closed, prefix_maximal or prefix_closed: by extensions of one term."""
    cuts = ["1:n - 1"] if mode.startswith("prefix") else ["1:n - 1", "2:n"]
    parts = " union all ".join(f"select array_to_string(string_split(gram, ' ')[{c}], ' ') part, cf from stats where n > 1" for c in cuts)
    keep = "best is null or best < cf" if "closed" in mode else "best is null"
    return f"""{stats_cte(tau, sigma)},
longer as (select part, max(cf) best from ({parts}) group by part)
select gram, n, cf from stats left join longer on part = gram where {keep}"""
