"""DuckDB SQL of the operators whose results are relations of words: repeated windows, benchmark windows, similar sets.

Written from the definitions and not from the Spark plans. Words are compared as text, never by hash.
"""

from __future__ import annotations

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_WORD = r"[^\x20\x09-\x0D]+"
#: Words of letters and digits, and of all that is beyond ASCII; upper case is gone before.
_ITEM_WORD = r"[0-9a-z\x{80}-\x{10FFFF}]+"


def _lower(text: str) -> str:
    return f"translate({text}, '{UPPER}', '{LOWER}')"


def _run(words: str, start: str, k: str) -> str:
    """The ``k`` words from ``start`` on as one text; words hold no space, so equal texts are equal runs."""
    return f"array_to_string(list_slice({words}, {start}, {start} + {k} - 1), ' ')"


def repeated_windows(width: int = 50) -> str:
    """(doc_id, n_words, n_removed, kept_sha256): a window that also starts in a document with a smaller id covers its words."""
    return f"""with w as (select doc_id, regexp_extract_all(coalesce(text, ''), '{_WORD}') as ws from documents),
        win as (select doc_id, i, {_run('ws', 'i', str(width))} as run from (select doc_id, ws, unnest(range(1, len(ws) - {width - 2})) as i from w)),
        own as (select run, min(doc_id) as owner from win group by run),
        again as (select doc_id, i from win join own using (run) where owner < doc_id),
        word as (select doc_id, i, ws[i] as word from (select doc_id, ws, unnest(range(1, len(ws) + 1)) as i from w)),
        marked as (select doc_id, i, word, coalesce(max(case when again.i is not null then 1 end) over (partition by doc_id order by i rows between {width - 1} preceding and current row), 0) as gone
            from word left join again using (doc_id, i)),
        kept as (select doc_id, sum(gone) as n_removed, string_agg(word, ' ' order by i) filter (where gone = 0) as t from marked group by doc_id)
        select w.doc_id, cast(len(ws) as bigint) as n_words, cast(coalesce(n_removed, 0) as bigint) as n_removed, sha256(coalesce(t, '')) as kept_sha256 from w left join kept using (doc_id)"""


def benchmark_windows(width: int = 13, share: int = 20) -> str:
    """What documents share with the benchmark: words hit, items, and the longest run of windows that follow each other in both.

    Shorter items are one window. Of longest matches the first in the document counts, then the item of the smaller id.
    """
    return f"""with d as (select doc_id, regexp_extract_all({_lower("coalesce(text, '')")}, '{_ITEM_WORD}') as ws from documents),
        b as (select item_id, regexp_extract_all({_lower("coalesce(text, '')")}, '{_ITEM_WORD}') as ws from benchmark),
        bw as (select item_id, k, j, {_run('ws', 'j', 'k')} as run from (select item_id, ws, least({width}, len(ws)) as k, unnest(range(1, len(ws) - least({width}, len(ws)) + 2)) as j from b where len(ws) > 0)),
        dw as (select doc_id, k, i, {_run('ws', 'i', 'k')} as run from (select doc_id, ws, k, unnest(range(1, len(ws) - k + 2)) as i from d, (select distinct k from bw))),
        met as materialized (select doc_id, item_id, i, j, dw.k from dw join bw using (k, run)),
        hit as (select doc_id, count(distinct p) as n_hit from (select doc_id, unnest(range(i, i + k)) as p from (select distinct doc_id, i, k from met)) group by doc_id),
        item as (select doc_id, count(*) as n_items, string_agg(s, ',' order by s) as ids from (select distinct doc_id, cast(item_id as varchar) as s from met) group by doc_id),
        runs as (select doc_id, item_id, min(i) as i, min(j) as j, max(k) + count(*) - 1 as words
            from (select *, i - row_number() over (partition by doc_id, item_id, i - j order by i) as part from met) group by doc_id, item_id, i - j, part),
        best as (select * from runs qualify row_number() over (partition by doc_id order by words desc, i, item_id, j) = 1)
        select doc_id, cast(len(ws) as bigint) as n_words, cast(coalesce(n_hit, 0) as bigint) as n_hit, cast(coalesce(n_items, 0) as bigint) as n_items, sha256(coalesce(ids, '')) as items_sha256,
            coalesce(n_hit, 0) > 0 and {share} * coalesce(n_hit, 0) >= len(ws) as contaminated,
            cast(coalesce(words, 0) as bigint) as longest_match, cast(i - 1 as bigint) as match_start, cast(best.item_id as varchar) as match_item, cast(j - 1 as bigint) as item_start
        from d left join hit using (doc_id) left join item using (doc_id) left join best using (doc_id)"""


def similar_sets(k: int = 5, percent: int = 80) -> str:
    """(doc_id, n_shingles, component_id): documents linked by the Jaccard index of their shingle sets, by recursion over links."""
    return f"""with recursive w as (select doc_id, regexp_extract_all({_lower("coalesce(text, '')")}, '{_WORD}') as ws from documents),
        sh as (select distinct doc_id, {_run('ws', 'i', 'k')} as run from (select doc_id, ws, least({k}, len(ws)) as k, unnest(range(1, len(ws) - least({k}, len(ws)) + 2)) as i from w where len(ws) > 0)),
        size as (select doc_id, count(*) as n from sh group by doc_id),
        met as (select x.doc_id as a, y.doc_id as b, count(*) as c from sh x join sh y on x.run = y.run and x.doc_id <> y.doc_id group by 1, 2),
        link as materialized (select a, b from met join size s on s.doc_id = a join size t on t.doc_id = b where 100 * c >= {percent} * (s.n + t.n - c)),
        reach(a, b) as (select doc_id, doc_id from w union select r.a, l.b from reach r join link l on l.a = r.b)
        select w.doc_id, cast(coalesce(n, 0) as bigint) as n_shingles, least_id as component_id from w left join size using (doc_id) join (select a, min(b) as least_id from reach group by a) on a = w.doc_id"""
