"""Contract queries: each runs its operator with production parameters over its whole table."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from . import decontam, html_tree, langid, lm_scoring, packing, pii, quality_crf, quality_rules, simhash, token_store

#: Documents' hits by plain joins of word windows, for DuckDB.
OP6_SQL = r"""
with words as (
    select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w
    from documents
), item_words as (
    select item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w
    from benchmark
), windows as (
    select distinct item_id, least(10, len(w)) as n, array_to_string(w[i:i + least(10, len(w)) - 1], ' ') as phrase
    from item_words, unnest(range(1, greatest(2, len(w) - 10 + 2))) as t(i)
    where len(w) > 0
), sizes as (
    select distinct n from windows
), places as (
    select doc_id, n, i, array_to_string(w[i:i + n - 1], ' ') as phrase
    from words, sizes, unnest(range(1, greatest(1, len(w) - n + 2))) as t(i)
), found as (
    select doc_id, item_id, i, p.n from places p join windows v on p.n = v.n and p.phrase = v.phrase
), hits as (
    select doc_id, count(distinct k) as n_hit from found, unnest(range(i, i + n)) as t(k) group by doc_id
), items as (
    select doc_id, count(*) as n_items, sha256(string_agg(item, ',' order by item)) as items_sha256
    from (select distinct doc_id, cast(item_id as varchar) as item from found) group by doc_id
), pos as (
    select doc_id, unnest(w) as term, unnest(range(1, len(w) + 1)) as i from words
), seen as (
    select term, count(*) as n from pos group by term
), numbered as (
    select row_number() over () as wid, item_id, string_split(phrase, ' ') as terms from windows
), spots as (
    select wid, unnest(terms) as term, unnest(range(1, len(terms) + 1)) as place from numbered
), rarest as (
    select wid, term from spots join seen using (term) qualify row_number() over (partition by wid order by n, place) = 1
), around as (
    select wid, doc_id, i from rarest join pos using (term)
), full_windows as (
    select wid, doc_id, a.i from around a join (select distinct wid, term, n_terms from spots join (select wid, count(distinct term) as n_terms from spots group by wid) using (wid)) t using (wid) join pos p using (doc_id, term)
    where p.i between a.i - 15 and a.i + 15
    group by wid, doc_id, a.i having count(distinct term) = any_value(t.n_terms)
), near as (
    select doc_id, count(distinct cast(item_id as varchar)) as n_near from full_windows join numbered using (wid) group by doc_id
)
select doc_id, cast(len(w) as bigint) as n_words, cast(coalesce(n_hit, 0) as bigint) as n_hit, cast(coalesce(n_items, 0) as bigint) as n_items,
    coalesce(items_sha256, sha256('')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated, cast(coalesce(n_near, 0) as bigint) as n_near
from words left join hits using (doc_id) left join items using (doc_id) left join near using (doc_id)
"""


#: The base columns of the quality rules.
RULES_SQL = r"""
with t as (
    select doc_id, coalesce(text, '') as text from documents
), words as (
    select doc_id, text, regexp_extract_all(text, '[^\x20\x09-\x0D]+') as w from t
), windows as (
    select doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] as gram from words, unnest(range(1, greatest(1, len(w) - 1))) as u(i)
), twice as (
    select doc_id, i from windows qualify count(*) over (partition by doc_id, gram) > 1
), repeated as (
    select doc_id, count(distinct k) as n from twice, unnest(range(i, i + 3)) as u(k) group by doc_id
), lines as (
    select doc_id, unnest(string_split(text, chr(10))) as line from t
), doubled as (
    select doc_id, count(*) - count(distinct line) as n from lines where regexp_matches(line, '[^\x20\x09-\x0D]') group by doc_id
), counts as (
    select doc_id, len(w)::bigint as n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::bigint as word_chars,
        (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::bigint as n_symbols, coalesce(d.n, 0)::bigint as n_dup_lines, coalesce(r.n, 0)::bigint as n_repeat_words
    from words left join doubled d using (doc_id) left join repeated r using (doc_id)
)
select *, n_words < 50 or 100 * n_repeat_words > 50 * n_words as base_failed from counts
"""

#: How many base spans of each kind the texts hold.
PRIVACY_SQL = r"""
with t as (
    select doc_id, coalesce(text, '') as text from documents
), found as (
    select doc_id, regexp_extract_all(text, '[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+') as emails, regexp_extract_all(text, '[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+') as ips,
        list_transform(regexp_extract_all(text, '[0-9](?:[\x20-]?[0-9])+'), lambda x: regexp_replace(x, '[^0-9]', '', 'g')) as numbers,
        list_transform(regexp_extract_all(text, '\+[0-9][\x20().0-9-]+[0-9]'), lambda x: length(regexp_replace(x, '[^0-9]', '', 'g'))) as calls
    from t
), digits as (
    select doc_id, place, length(number) as n, unnest(string_split(reverse(number), ''))::int as d, unnest(range(length(number))) as i
    from (select doc_id, unnest(numbers) as number, unnest(range(len(numbers))) as place from found) where length(number) between 12 and 19
), luhn as (
    select doc_id, place, sum(case when i % 2 = 0 then d when d > 4 then 2 * d - 9 else 2 * d end) % 10 as rest from digits group by doc_id, place
), cards as (
    select doc_id, count(*) as n from luhn where rest = 0 group by doc_id
)
select doc_id, len(emails)::bigint as n_email, len(list_filter(ips, lambda x: list_aggregate(list_transform(string_split(x, '.'), lambda y: y::hugeint <= 255), 'bool_and')))::bigint as n_ip,
    coalesce(cards.n, 0)::bigint as n_card, len(list_filter(calls, lambda x: x between 9 and 15))::bigint as n_phone
from found left join cards using (doc_id)
"""


def _read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_quality_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_crf.apply(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "labels"))


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    trusted = _read(spark, sf_dir, "labels").where("quality = 1").select("doc_id")
    return quality_rules.apply(_read(spark, sf_dir, "documents"), trusted)


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.cluster(_read(spark, sf_dir, "documents"))


def op4_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    trusted = _read(spark, sf_dir, "labels").where("quality = 1").select("doc_id")
    return lm_scoring.apply(_read(spark, sf_dir, "documents"), trusted)


def op5_language_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.apply(_read(spark, sf_dir, "documents"))


def op6_positional_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.apply(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "benchmark")).drop("item_ids", "near_ids")


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_read(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op8_style_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_tree.extract(_read(spark, sf_dir, "pages"))


def op9_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_store.write_store(_read(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json")).records()


def op10_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.apply(_read(spark, sf_dir, "documents"))


def rules_base_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What op2 counts before its method judges."""
    return quality_rules.rate(_read(spark, sf_dir, "documents"), np.zeros(1)).drop("score", "kept")


def privacy_base_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What op10 counts before its method adds spans."""
    return pii.find(_read(spark, sf_dir, "documents"), None).select("doc_id", *(f"n_{k}" for k in pii.KINDS))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_quality_crf": op1_quality_crf,
        "op2_quality_rules": op2_quality_rules,
        "op3_simhash": op3_simhash,
        "op4_lm_scoring": op4_lm_scoring,
        "op5_language_codes": op5_language_codes,
        "op6_positional_index": op6_positional_index,
        "op7_packing": op7_packing,
        "op8_style_tree": op8_style_tree,
        "op9_token_store": op9_token_store,
        "op10_pii": op10_pii,
        "rules_base_columns": rules_base_columns,
        "privacy_base_columns": privacy_base_columns,
    }


def oracle_sql() -> dict[str, str]:
    return {"op6_positional_index": OP6_SQL, "rules_base_columns": RULES_SQL, "privacy_base_columns": PRIVACY_SQL}
