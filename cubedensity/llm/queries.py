"""The op queries, as the driver registers them. Those that SQL can express have an oracle, written from the definition;
fingerprints and hashes with a seed, learned models and trees are tested against brute force instead."""

from __future__ import annotations

from cubedensity.llm import decontam, linededup, mainhtml, packing, pii, quality, secrets, simhash, toxicity, warc
from cubedensity.llm.common import table


def op1_surrogates(spark, sf_dir):
    return pii.replace(table(spark, sf_dir, "documents"), pii.key_of(spark))


def op2_simhash(spark, sf_dir):
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op3_decision_list(spark, sf_dir):
    return quality.judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_warc_derivatives(spark, sf_dir):
    return warc.derive(warc.responses(table(spark, sf_dir, "pages")))


def op5_suffix_array(spark, sf_dir):
    return decontam.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op6_line_templates(spark, sf_dir):
    return linededup.drop_templates(table(spark, sf_dir, "documents"))


def op7_length_buckets(spark, sf_dir):
    return packing.pack(table(spark, sf_dir, "documents"))


def op8_tree_scoring(spark, sf_dir):
    return mainhtml.main_text(table(spark, sf_dir, "pages"))


def op9_trigram_secrets(spark, sf_dir):
    return secrets.digest(table(spark, sf_dir, "documents"))


def op10_counterfactual(spark, sf_dir):
    return toxicity.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def queries():
    return {f.__name__: f for f in (op1_surrogates, op2_simhash, op3_decision_list, op4_warc_derivatives, op5_suffix_array, op6_line_templates, op7_length_buckets, op8_tree_scoring, op9_trigram_secrets, op10_counterfactual)}


_LOWER = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _windows_sql() -> str:
    """Words of texts that windows of items cover: every window of every item against every stretch of every text."""
    words = "regexp_extract_all(" + _LOWER.format("coalesce(text, '')") + r", '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
    cut = lambda size: f"list_transform(range(1, len(w) - {size} + 2), lambda i: array_to_string(w[i:i + {size} - 1], ' '))"
    return (
        f"with d as materialized (select row_number() over () as r, doc_id, {words} as w from documents), "
        f"b as (select item_id::varchar as item_id, w, least({decontam.WINDOW}, len(w)) as size from (select item_id, {words} as w from benchmark) where len(w) > 0), "
        f"win as materialized (select distinct item_id, size, unnest({cut('size')}) as key from b), sizes as (select distinct size from win), "
        f"spots as (select r, size, unnest({cut('size')}) as key, unnest(range(1, len(w) - size + 2)) as pos from d, sizes where len(w) >= size), "
        "hit as materialized (select r, pos, s.size, item_id from spots s join win using (key, size)), "
        "n as (select r, count(distinct p) as n from (select r, unnest(range(pos, pos + size)) as p from hit) group by r), "
        "i as (select r, count(distinct item_id) as n, string_agg(distinct item_id, ',' order by item_id) as ids from hit group by r) "
        "select doc_id, len(w)::bigint as n_words, coalesce(n.n, 0)::bigint as n_hit, coalesce(i.n, 0)::bigint as n_items, sha256(coalesce(ids, '')) as items_sha256, coalesce(n.n, 0) > 0 as contaminated "
        "from d left join n using (r) left join i using (r)"
    )


def _spans_sql() -> str:
    """Spans of every rule run over every text: places from the lengths of matches and of what lies between."""
    kinds, parts = [*secrets.BASE, *secrets.MORE], []
    for k, rule in enumerate(kinds):
        pattern = "'" + rule.pattern.replace("'", "''").replace(r"[^\s", r"[^\s\x0B") + "'"
        gap = f"string_split_regex(t, {pattern})"
        size = lambda items, upto: f"coalesce(list_sum(list_transform(({items})[1:{upto}], lambda y: length(y))), 0)"
        every, group = f"regexp_extract_all(t, {pattern})", f"regexp_extract_all(t, {pattern}, {rule.group})"
        made = f"list_transform({every}, lambda x, i: {{'start': ({size(gap, 'i')} + {size(every, 'i - 1')})::bigint, 'k': {k}, 'end': ({size(gap, 'i')} + {size(every, 'i')})::bigint, 'n': length(({group})[i])}})"
        parts.append(f"list_filter({made}, lambda z: z.n >= {rule.least})")
    names = "[" + ", ".join(f"'{r.kind}'" for r in kinds) + "]"
    written = lambda spans: f"array_to_string(list_transform({spans}, lambda z: ({names})[z.k + 1] || ':' || z.start || ':' || z.end), ',')"
    base = f"list_filter(found, lambda z: z.k < {len(secrets.BASE)})"
    count = lambda k: f"len(list_filter(found, lambda z: z.k = {k}))::bigint"
    return (
        f"select doc_id, {', '.join(f'{count(k)} as n_{r.kind}' for k, r in enumerate(secrets.BASE))}, sha256({written(base)}) as base_sha256, {written('found')} as spans "
        f"from (select doc_id, list_sort({' || '.join(parts)}) as found from (select doc_id, coalesce(text, '') as t from documents))"
    )


def oracle_sql():
    return {"op5_suffix_array": _windows_sql(), "op9_trigram_secrets": _spans_sql()}
