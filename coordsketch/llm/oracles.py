"""SQL for the text queries that SQL can express, over the same tables."""

from __future__ import annotations

from .quality import LEAST_DOCUMENTS, MAX_REPEAT_PERCENT, MEASURES, MIN_WORDS, SPREADS

_SPACE = r"[\x20\x09-\x0D]"


def _without(text: str, signs: str) -> str:
    return f"regexp_replace({text}, '{signs}', '', 'g')"


CHAT = rf"""
with c as (
  select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select -7, 0, 'user', '</s>[INST] ok [/INST]' union all select -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
sized as (select *, 17 + length(role) + length(text) + 2 * length(role) - length({_without("role", "[[<\\\\]")}) - length(replace(role, chr(10), '')) + length(text) - length({_without("text", "[[<\\\\]")}) as chars from c)
select conv_id, count(*) as n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn)) as turns_sha256,
  coalesce(sum(length(text)) filter (where role = 'assistant'), 0)::bigint as loss_chars,
  sha256(coalesce(string_agg(text, '' order by turn) filter (where role = 'assistant'), '')) as loss_sha256, sum(chars)::bigint as formatted_chars
from sized group by conv_id"""


def _quality() -> str:
    long = " union all ".join(f"select doc_id, lang, source, base_failed, '{k}' as measure, {k} as bin, {d} as least, {'true' if 'low' in sides else 'false'} as low_too from v" for k, (_, sides, d) in MEASURES.items())
    values = ", ".join(f"case when n_words > 0 then ({e.replace(' div ', ' // ')}) end as {k}" for k, (e, _, _) in MEASURES.items())

    def level(by: str) -> str:
        at = ", ".join(f"s[(len(s) * {q} + 99) // 100] as q{q}" for q in (25, 50, 75))
        return f"select {by}measure, len(s) as total, {at} from (select {by}measure, list_sort(list(bin)) as s from long where not base_failed group by all)"

    pick = {q: f"case when own.total >= {LEAST_DOCUMENTS} then own.q{q} when wide.total >= {LEAST_DOCUMENTS} then wide.q{q} else every_.q{q} end" for q in (25, 50, 75)}
    return rf"""
with d as (select doc_id, lang, source, coalesce(text, '') as t from documents),
w as (select *, [x for x in string_split_regex(t, '{_SPACE}+') if x <> ''] as ws, [x for x in string_split(t, chr(10)) if regexp_matches(x, '[^\x20\x09-\x0D]')] as ls from d),
tri as (select doc_id, i, ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2] as g from (select doc_id, ws, unnest(range(1, len(ws) - 1)) as i from w)),
hit as (select doc_id, i from (select *, count(*) over (partition by doc_id, g) as n from tri) where n > 1),
cover as (select doc_id, count(distinct j) as n from (select doc_id, unnest([i, i + 1, i + 2]) as j from hit) group by 1),
b as (select w.doc_id, lang, source, len(ws)::bigint as n_words, length({_without("t", _SPACE)})::bigint as word_chars,
  (length(t) - length({_without("t", "[#*$%&|<>]")}))::bigint as n_symbols, (length(t) - length({_without("t", "[A-Z]")}))::bigint as n_capitals,
  len(ls)::bigint as n_lines, (len(ls) - len(list_distinct(ls)))::bigint as n_dup_lines, coalesce(n, 0)::bigint as n_repeat_words from w left join cover using (doc_id)),
v as (select *, n_words < {MIN_WORDS} or 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words as base_failed, {values} from b),
long as ({long}),
own as ({level("lang, source, ")}), wide as ({level("lang, ")}), every_ as ({level("")}),
lim as (select own.lang, own.source, own.measure, {pick[25]} as a, {pick[50]} as m, {pick[75]} as z from own join wide on own.lang is not distinct from wide.lang and own.measure = wide.measure join every_ on own.measure = every_.measure),
bad as (select doc_id, bool_or(coalesce(bin > m + greatest({SPREADS} * (z - m), least) or (low_too and bin < m - greatest({SPREADS} * (m - a), least)), false)) as out_
  from long left join lim on long.lang is not distinct from lim.lang and long.source is not distinct from lim.source and long.measure = lim.measure group by 1)
select v.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, not base_failed and not out_ as kept, {", ".join(MEASURES)} from v join bad using (doc_id)"""


#: The table of CRC-32 by its rule (the reversed polynomial 0xEDB88320), and the checksum of a text's UTF-8 bytes.
_CRC_TABLE = """(with recursive t as (select i, 0 as k, i::bigint as c from range(256) r(i)
  union all select i, k + 1, case when c & 1 = 1 then xor(c >> 1, 3988292384) else c >> 1 end from t where k < 8) select list(c order by i) from t where k = 8)"""


def _crc(text: str) -> str:
    """text as SQL; a column `crc` with the table has to be there."""
    raw = f"[('0x' || x)::bigint for x in regexp_extract_all(hex(encode({text})), '..')]"
    return f"xor(list_reduce(list_prepend(4294967295::bigint, {raw}), lambda c, x: xor(c >> 8, crc[(xor(c, x) & 255) + 1])), 4294967295::bigint)"


SHARDS = f"""
with d as (select doc_id, source, strlen(coalesce(text, ''))::bigint + 1 as size, {_crc("coalesce(text, '')")} as text_crc32, md5('interleave:' || coalesce(doc_id::varchar, 'null')) as draw, coalesce('=' || source, '') as stratum
  from documents, (select {_CRC_TABLE} as crc)),
r as (select *, (2.0::double * row_number() over (partition by stratum order by draw, doc_id nulls first, text_crc32) - 1) / (2.0::double * count(*) over (partition by stratum)) as fraction from d),
p as (select *, row_number() over (order by fraction, stratum, draw, doc_id nulls first, text_crc32) - 1 as place, count(*) over () as n from r),
s as (select *, (place * 16 // n)::int as shard from p)
select doc_id, size, text_crc32, 'rows' as law, shard, (place - (shard * n + 15) // 16)::bigint as slot, null::int as grown_shard from s"""

ORACLES = {"op3_chat_event_fold": CHAT, "op4_stratified_interleave": SHARDS, "op5_adaptive_quality": _quality()}
