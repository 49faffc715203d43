"""The registered queries of this subpackage and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gainbound.llm import chat, decontaminate, jaccard, langid, mixing, quality, sharding, substrings, toxicity, warc
from gainbound.llm.common import table


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), decontaminate.is_contaminated().alias("contaminated"),
    )


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nonnegative rates that bring the languages' expected tokens to smoothed shares of the present total, beside what the document's likeliest domain should have and has."""
    mixed, model, fit = mixing.mix(table(spark, sf_dir, "documents").select("doc_id", "text", "lang"), least=0.0)
    totals = F.create_map(*[F.lit(x) for d, want, got in zip(model.domains, fit.targets.tolist(), fit.reached.tolist(), strict=True) for x in (d, [want, got])])[F.col("_domain")]
    return mixed.select("doc_id", F.col("_tokens").alias("tokens"), F.col("_domain").alias("domain"), F.col("_rate").alias("rate"), F.col("_copies").alias("copies"), totals[0].alias("domain_target"), totals[1].alias("domain_reached"))


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.classify(table(spark, sf_dir, "documents"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality.judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return judged.select("doc_id", *quality.COUNTS, "base_failed", "kept", "score")


def quality_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What op5's base rules see: its counts before any tree, which SQL can express."""
    return quality.measure(table(spark, sf_dir, "documents")).select("doc_id", *quality.COUNTS, quality.base_failed().alias("base_failed"))


def op6_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.repair_roles(table(spark, sf_dir, "conversations"))


def op7_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.archive_and_read(table(spark, sf_dir, "pages"))


def op8_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.similarity_classes(table(spark, sf_dir, "documents"))


def op9_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substrings.dedup_substrings(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "n_removed", "kept_sha256")


def op10_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign_shards(table(spark, sf_dir, "documents"), 16)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_mix_sources": op1_mix_sources,
    "op2_decontaminate": op2_decontaminate,
    "op3_language_id": op3_language_id,
    "op4_toxicity": op4_toxicity,
    "op5_quality_rules": op5_quality_rules,
    "op6_chat_format": op6_chat_format,
    "op7_warc": op7_warc,
    "op8_jaccard_join": op8_jaccard_join,
    "op9_substring_dedup": op9_substring_dedup,
    "op10_shards": op10_shards,
    "quality_counts": quality_counts,
}

_ALNUM = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_GRAPHIC = r"[^\x20\x09-\x0D]+"
_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

ORACLE = {
    "op2_decontaminate": f"""
with d as (select doc_id, regexp_extract_all({_LOWER}, '{_ALNUM}') as w from documents),
b as (select cast(item_id as varchar) as item, regexp_extract_all({_LOWER}, '{_ALNUM}') as w from benchmark where item_id is not null),
p as (select distinct item, least(13, len(w)) as k, array_to_string(w[i:i + least(13, len(w)) - 1], ' ') as phrase
      from (select item, w, unnest(range(1, len(w) - least(13, len(w)) + 2)) as i from b where len(w) > 0)),
k as (select distinct k from p),
g as (select doc_id, i, k, array_to_string(w[i:i + k - 1], ' ') as phrase
      from (select doc_id, w, k, unnest(range(1, len(w) - k + 2)) as i from d, k where len(w) >= k)),
h as (select doc_id, i, g.k, item from g join p on g.phrase = p.phrase and g.k = p.k),
c as (select doc_id, count(distinct j) as n_hit from (select doc_id, unnest(range(i, i + k)) as j from h) group by doc_id),
t as (select doc_id, count(*) as n_items, string_agg(item, ',' order by item) as items from (select distinct doc_id, item from h) group by doc_id)
select d.doc_id, cast(len(w) as bigint) as n_words, cast(coalesce(n_hit, 0) as bigint) as n_hit, cast(coalesce(n_items, 0) as bigint) as n_items,
       sha256(coalesce(items, '')) as items_sha256, coalesce(n_hit, 0) > 0 and 20 * coalesce(n_hit, 0) >= len(w) as contaminated
from d left join c using (doc_id) left join t using (doc_id)""",
    "quality_counts": f"""
with d as (select doc_id, coalesce(text, '') as text, regexp_extract_all(coalesce(text, ''), '{_GRAPHIC}') as w from documents),
g as (select doc_id, i, array_to_string(w[i:i + 4], ' ') as phrase from (select doc_id, w, unnest(range(1, len(w) - 3)) as i from d where len(w) >= 5)),
t as (select doc_id, i from (select doc_id, i, count(*) over (partition by doc_id, phrase) as n from g) where n > 1),
r as (select doc_id, count(distinct j) as n from (select doc_id, unnest(range(i, i + 5)) as j from t) group by doc_id),
l as (select doc_id, count(*) - count(distinct line) as n from (select doc_id, unnest(str_split(text, chr(10))) as line from d) where regexp_matches(line, '{_GRAPHIC}') group by doc_id)
select d.doc_id, cast(len(w) as bigint) as n_words, cast(length(array_to_string(w, '')) as bigint) as word_chars, cast(len(regexp_extract_all(text, '[#*$%&|<>]')) as bigint) as n_symbols,
       cast(coalesce(l.n, 0) as bigint) as n_dup_lines, cast(coalesce(r.n, 0) as bigint) as n_repeat_words, len(w) < 10 or 100 * coalesce(r.n, 0) > 20 * len(w) as base_failed
from d left join r using (doc_id) left join l using (doc_id)""",
    "op9_substring_dedup": f"""
with d as (select doc_id, regexp_extract_all(coalesce(text, ''), '{_GRAPHIC}') as w from documents),
g as (select doc_id, i, array_to_string(w[i:i + 19], ' ') as phrase
      from (select doc_id, w, unnest(range(1, len(w) - 18)) as i from d where len(w) >= 20)),
r as (select doc_id, i from (select doc_id, i, row_number() over (partition by phrase order by doc_id, i) as n from g) where n > 1),
x as (select distinct doc_id, j from (select doc_id, unnest(range(i, i + 20)) as j from r)),
k as (select doc_id, string_agg(word, ' ' order by j) as kept, count(*) as n
      from (select doc_id, unnest(w) as word, unnest(range(1, len(w) + 1)) as j from d) as words anti join x using (doc_id, j) group by doc_id)
select d.doc_id, cast(len(w) as bigint) as n_words, cast(len(w) - coalesce(n, 0) as bigint) as n_removed, sha256(coalesce(kept, '')) as kept_sha256
from d left join k using (doc_id)""",
    "op7_warc": """
with p as (select page_id, coalesce(html, '') as html from pages),
g as (select page_id, html, strlen(html) as n, sha1(html) as h, max(page_id) over (partition by html) as holder from p)
select page_id, cast(n as bigint) as payload_bytes,
       array_to_string([substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + cast((cast('0x' || substr(h, 1 + 5 * (i // 4), 5) as integer) >> (15 - 5 * (i % 4))) & 31 as integer), 1) for i in range(32)], '') as payload_digest,
       case when page_id = holder then 'response' else 'revisit' end as record_type,
       case when page_id = holder then null else holder end as refers_to
from g""",
    "op8_jaccard_join": f"""
with recursive t as (select text, min(doc_id) as id, count(*) as copies, regexp_extract_all(text, '{_GRAPHIC}') as w from documents where text is not null group by text),
s as (select distinct id, array_to_string(w[i:i + least(5, len(w)) - 1], ' ') as gram from (select id, w, unnest(range(1, len(w) - least(5, len(w)) + 2)) as i from t where len(w) > 0)),
n as (select id, count(*) as n from s group by id),
c as (select a.id as a, b.id as b, count(*) as common from s a join s b on a.gram = b.gram and a.id <> b.id group by 1, 2),
l as (select c.a, c.b from c join n x on x.id = c.a join n y on y.id = c.b where 10 * common >= 8 * (x.n + y.n - common)),
r(id, other) as (select id, id from t union select r.id, l.b from r join l on l.a = r.other),
k as (select id, min(other) as class_id from r group by id),
m as (select l.a as id, count(*) as text_links, sum(t.copies) as links from l join t on t.id = l.b group by l.a)
select d.doc_id, coalesce(k.class_id, d.doc_id) as class_id, cast(coalesce(m.links, 0) + coalesce(t.copies, 1) - 1 as bigint) as n_links, cast(coalesce(m.text_links, 0) as bigint) as n_text_links
from documents d left join t on t.text = d.text left join k on k.id = t.id left join m on m.id = t.id""",
    "op10_shards": """
with recursive d as (select doc_id, text, strlen(coalesce(text, '')) + 1 as size, min(doc_id) over (partition by text) as key from documents),
g as (select key, sum(size)::bigint as size, row_number() over (order by key) as n from d group by key),
s as (select list(size order by key) as sizes, sum(size)::bigint as total, max(size) as most from g),
b(low, high) as (
    select greatest(most, (total + 15) // 16), total from s
    union all
    select case when runs <= 16 then low else mid + 1 end, case when runs <= 16 then mid else high end
    from (select low, high, (low + high) // 2 as mid, list_reduce(sizes, lambda a, x: case when a % 1099511627776 + x <= (low + high) // 2 then a + x else (a // 1099511627776 + 1) * 1099511627776 + x end, 1099511627776) // 1099511627776 as runs
          from b, s where low < high)),
c as (select min(high) as cap from b),
f(n, shard, used) as (
    select 1, 0, size from g where n = 1
    union all
    select f.n + 1, case when f.used + g.size <= cap then f.shard else f.shard + 1 end, case when f.used + g.size <= cap then f.used + g.size else g.size end
    from f join g on g.n = f.n + 1, c),
bytes as (select list_transform(range(256), lambda i: list_reduce([1, 2, 3, 4, 5, 6, 7, 8], lambda a, k: case when a & 1 = 1 then xor(3988292384, a >> 1) else a >> 1 end, i::bigint)) as entry),
x as (select doc_id, list_reduce(list_transform(range(strlen(coalesce(text, ''))), lambda i: cast('0x' || substr(h, 1 + 2 * i, 2) as bigint)), lambda a, v: xor(a >> 8, entry[1 + (xor(a, v) & 255)]), 4294967295) as crc
      from (select doc_id, text, hex(encode(coalesce(text, ''))) as h from documents), bytes)
select d.doc_id, cast(d.size as bigint) as size, xor(x.crc, 4294967295) as text_crc32, 'bytes' as law, cast(f.shard as integer) as shard,
       row_number() over (partition by f.shard order by d.doc_id) - 1 as slot, cast(null as integer) as grown_shard
from d join g using (key) join f using (n) join x using (doc_id)""",
}
