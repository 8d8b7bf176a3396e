"""DuckDB SQL for those operators that SQL can express."""

from __future__ import annotations

from comotion.llm import quality_rules, sharding

GAP = r"[\x20\x09-\x0D]"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def placement() -> str:
    owner = ", ".join(map(str, sharding.fill(sharding.shard_names(), sharding.SLOTS)))
    return f"""with k as (select *, cast('0x' || substr(md5(coalesce(cast(doc_id as varchar), '')), 1, 15) as bigint) % {sharding.SLOTS} as slot from documents)
        select *, cast(([{owner}])[slot + 1] as bigint) as shard from k"""


def rules() -> str:
    stops = ", ".join(f"'{w}'" for w in sorted({form for w in quality_rules.STOP_WORDS for form in (w, w.capitalize())}))
    measure = {
        "n_words": "n_words",
        "mean_word_chars": "coalesce(word_chars / nullif(n_words, 0), 0)",
        "symbols_per_word": "coalesce(n_symbols / nullif(n_words, 0), 0)",
        "capitals_per_char": "coalesce(capitals / nullif(word_chars, 0), 0)",
        "stop_words_per_word": "coalesce(stops / nullif(n_words, 0), 0)",
        "dup_lines_per_line": "coalesce(n_dup_lines / nullif(n_lines, 0), 0)",
    }
    tests = [f"{measure[r.measure]} >= {r.low}" for r in quality_rules.RULES] + [f"{measure[r.measure]} <= {r.high}" for r in quality_rules.RULES if r.high < float("inf")]
    return f"""with t as (select row_number() over () as k, doc_id, coalesce(text, '') as t from documents),
    w as materialized (select *, list_filter(regexp_split_to_array(t, '{GAP}+'), lambda x: x <> '') as ws, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) as ls from t),
    g as materialized (select k, i, array_to_string(ws[i:i+4], ' ') as g from w, unnest(range(1, len(ws) - 3)) as u(i)),
    twice as (select k, g from g group by k, g having count(*) > 1),
    spots as (select distinct g.k, g.i + o as p from g join twice using (k, g), unnest(range(5)) as v(o)),
    covered as (select k, count(*) as n from spots group by k),
    m as (select w.k, doc_id, cast(len(ws) as bigint) as n_words, cast(length(regexp_replace(t, '{GAP}', '', 'g')) as bigint) as word_chars,
        cast(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) as bigint) as n_symbols, cast(len(ls) - len(list_distinct(ls)) as bigint) as n_dup_lines, len(ls) as n_lines,
        cast(coalesce(covered.n, 0) as bigint) as n_repeat_words, length(t) - length(regexp_replace(t, '\\p{{Lu}}', '', 'g')) as capitals, len(list_filter(ws, lambda x: x in ({stops}))) as stops
        from w left join covered on covered.k = w.k),
    b as (select *, (n_words < 10 or 100 * n_repeat_words > 20 * n_words) as base_failed from m)
    select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, not base_failed and {' and '.join(tests)} as kept from b"""


def classes() -> str:
    return f"""with recursive t as (select doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '{GAP}+'), lambda x: x <> '') as ws from documents),
    s as materialized (select distinct doc_id, g from (
        select doc_id, array_to_string(ws[i:i+4], ' ') as g from t, unnest(range(1, len(ws) - 3)) as u(i) union all
        select doc_id, array_to_string(ws, ' ') from t where len(ws) between 1 and 4)),
    n as materialized (select t.doc_id, count(g) as n from t left join s using (doc_id) group by t.doc_id),
    o as (select a.doc_id as a, b.doc_id as b, count(*) as o from s a join s b on a.g = b.g and a.doc_id < b.doc_id group by 1, 2),
    e as materialized (select a, b from o join n x on x.doc_id = a join n y on y.doc_id = b where 100 * o >= 80 * (x.n + y.n - o)),
    f as materialized (select a, b from e union all select b, a from e),
    r(d, c) as (select doc_id, doc_id from n union select f.b, r.c from r join f on f.a = r.d)
    select n.doc_id, cast(n.n as bigint) as n_shingles, min(r.c) as component_id from n join r on r.d = n.doc_id group by n.doc_id, n.n"""
