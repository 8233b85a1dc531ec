"""DuckDB SQL of the operators that SQL can express, written apart from them."""

from __future__ import annotations

from .licenses import BASE, COVER, DRIFT, NOTICES

WORDS = r"regexp_extract_all(t, '[^\x20\x09-\x0D]+')"


def quality() -> str:
    return rf"""
with d as (select row_number() over () r, doc_id, coalesce(text, '') t from documents),
w as (select r, doc_id, t, {WORDS} w, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) l from d),
g as (select r, w, unnest(range(1, len(w) - 3)) i from w where len(w) > 4),
k as (select r, i, array_to_string(w[i:i + 4], ' ') key from g),
x as (select r, i from k where (r, key) in (select r, key from k group by 1, 2 having count(*) > 1)),
n as (select r, count(distinct i + o) n from x cross join range(5) s(o) group by 1),
m as (select w.r, doc_id, cast(len(w) as bigint) n_words, cast(length(array_to_string(w, '')) as bigint) word_chars,
  cast(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) as bigint) n_symbols,
  cast(len(l) - len(list_distinct(l)) as bigint) n_dup_lines, cast(coalesce(n, 0) as bigint) n_repeat_words, len(l) n_lines,
  len(list_filter(w, lambda x: regexp_matches(x, '[^\x00-\x40\x5B-\x60\x7B-\x7F]'))) n_letters from w left join n on w.r = n.r)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_words < 10 or 100 * n_repeat_words > 20 * n_words base_failed,
  not (n_words < 10 or 100 * n_repeat_words > 20 * n_words or 10 * n_symbols > word_chars or 10 * n_dup_lines > 3 * n_lines or word_chars > 25 * n_words or word_chars < 2 * n_words or 2 * n_letters < n_words) kept
from m"""


def licenses() -> str:
    """Base phrases by comparing word lists at every place; notices by chains of equal word pairs, lengthened step by step."""
    base = ", ".join(f"('{p.label}', {p.words.split()!r}::varchar[])" for p in BASE)
    notes = ", ".join(f"({k}, '{p.label}', {p.words.split()!r}::varchar[], {p.must.split()!r}::varchar[])" for k, p in enumerate(NOTICES))
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    return rf"""
with recursive d as (select row_number() over () r, doc_id, regexp_extract_all(translate(coalesce(text, ''), '{upper}', '{lower}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') w from documents),
bp(label, pw) as (values {base}),
np(phrase, label, pw, must) as (values {notes}),
base as (select r, label, i - 1 place from (select r, w, label, pw, unnest(range(1, len(w) - len(pw) + 2)) i from d, bp) where w[i:i + len(pw) - 1] = pw),
tp as (select phrase, len(pw) - 1 pairs, i - 1 i, pw[i] a, pw[i + 1] b from (select phrase, pw, unnest(range(1, len(pw))) i from np)),
dp as (select r, i - 1 t, w[i] a, w[i + 1] b from (select r, w, unnest(range(1, len(w))) i from d)),
m as (select r, phrase, pairs, t, i, t - i diag from dp join tp using (a, b)),
anchors as (select distinct r, phrase, pairs, diag from m),
bm as (select x.r, x.phrase, x.pairs, x.diag, m.t, m.i from anchors x join m on m.r = x.r and m.phrase = x.phrase and m.diag between x.diag and x.diag + {DRIFT}),
likely as (select r, phrase, pairs, diag from bm group by all having count(distinct i) >= {COVER} * pairs),
cm as (select bm.* from bm join likely using (r, phrase, pairs, diag)),
chain(r, phrase, pairs, diag, t, i, n) as (
  select r, phrase, pairs, diag, t, i, 1 from cm
  union
  select c.r, c.phrase, c.pairs, c.diag, m.t, m.i, c.n + 1 from chain c join cm m on m.r = c.r and m.phrase = c.phrase and m.diag = c.diag and m.t > c.t and m.i > c.i),
held as (select r, phrase, diag, list(distinct a) || list(distinct b) ws from cm join tp using (phrase, i) group by all),
notes as (select c.r, np.label, max(n / c.pairs) cover from chain c join np using (phrase) join held h using (r, phrase, diag)
  where list_has_all(h.ws, np.must) group by all having max(n / c.pairs) >= {COVER}),
bases as (select r, count(*) n_base, cast(min(place) as bigint) first_word, cast(max(place) as bigint) last_word, list(distinct label) ls from base group by r),
others as (select r, list(distinct label) ls, max(cover) cover from notes group by r)
select doc_id, cast(len(w) as bigint) n_words, coalesce(n_base, 0) n_base, first_word, last_word, coalesce(array_to_string(list_sort(b.ls), ','), '') base_labels,
  coalesce(array_to_string(list_sort(list_distinct(coalesce(b.ls, []) || coalesce(o.ls, []))), ','), '') labels,
  cast(case when n_base > 0 then 1 else coalesce(cover, 0) end as double) score
from d left join bases b on d.r = b.r left join others o on d.r = o.r"""


def warc() -> str:
    return r"""
with p as (select page_id, coalesce(url, '') url, coalesce(html, '') h, octet_length(encode(coalesce(html, ''))) n from pages),
m as (select h, max(page_id) top from p group by 1)
select page_id, trim(regexp_replace(url, '[\r\n]', '', 'g')) uri, cast(n as bigint) payload_bytes, sha1(p.h) payload_digest,
  case when n >= 1000 and page_id < top then 'revisit' else 'response' end record_type, case when n >= 1000 and page_id < top then top end refers_to
from p join m on p.h = m.h"""


ORACLES = {"op6_license_scan": licenses(), "op9_quality_rules": quality(), "op10_warc": warc()}
