"""Transformation, sampling, annealing, tuning-data and composition workloads."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from corpusmill.operators import dedup, sampling, transform
from corpusmill.schema import FILES, TOKENS, files, table, tokens
from corpusmill.workloads.catalog import add, both
from corpusmill.workloads.fixtures import CODE_VALUES, code_files


def esc(p: str) -> str:
    return p.replace("'", "''")


docs = lambda s, d: table(s, d, "documents")
NOTICED = r"""l as (select *, string_split(text, chr(10)) as ls, ltrim(text, ' ' || chr(9) || chr(10)) as head from files), f as (select *, list_transform(ls, lambda x: case when regexp_matches(x, '^\s*(#|//)') then 1 when trim(x) = '' then 0 else 2 end) as fl from l),
g as (select *, case when list_contains(fl, 2) then fl[1:list_position(fl, 2) - 1] else fl end as lead from f), h as (select *, case when list_contains(lead, 1) then len(lead) - list_position(list_reverse(lead), 1) + 1 else 0 end as n from g)
select file_id, case when not regexp_matches(text, '[Cc]opyright') then text when starts_with(head, '/*') then case when instr(head, '*/') > 0 and regexp_matches(substr(head, 1, instr(head, '*/')), '[Cc]opyright') then regexp_replace(substr(head, instr(head, '*/') + 2), '^\s+', '') else text end
 when len(list_filter(ls[1:n], lambda x: regexp_matches(x, '[Cc]opyright'))) > 0 then array_to_string(ls[n + 1:], chr(10)) else text end as text from h"""
add("xform_strip_notice_head", lambda s, d: code_files(s).select("file_id", transform.strip_notice(F.col("text")).alias("text")), f"with {CODE_VALUES}, {NOTICED}")
add("xform_notice_documents", lambda s, d: docs(s, d).select(F.col("doc_id").alias("file_id"), transform.strip_notice(F.col("text")).alias("text")), f"with files as (select doc_id as file_id, text from documents), {NOTICED}")
add(
    "xform_mask_names", lambda s, d: code_files(s).unionByName(s.createDataFrame([(100, "python", "# Author: Jane Q. Doe\nSigned-off-by: John Smith <js@x.org>\nx = 1\n")], "file_id long, lang string, text string")).select("file_id", transform.mask_names(F.col("text")).alias("text")),
    f"with {CODE_VALUES}, u as (select file_id, text from files union all select 100, '# Author: Jane Q. Doe' || chr(10) || 'Signed-off-by: John Smith <js@x.org>' || chr(10) || 'x = 1' || chr(10)) select file_id, regexp_replace(regexp_replace(text, '{transform.NAME_MAIL}', '<name>\\1', 'g'), '{transform.NAMED}', '\\1<name>', 'g') as text from u",
)
add("xform_strip_license_lines", lambda s, d: docs(s, d).select("doc_id", F.md5(transform.strip_notice(F.col("text"), "anywhere")).alias("h")), f"select doc_id, md5(regexp_replace(text, '{transform.LICENSE_LINE}', '', 'g')) as h from documents")
add("xform_notice_share", lambda s, d: code_files(s).agg(F.round(F.avg(F.col("text").rlike("[Cc]opyright").cast("double")), 6).alias("share")), f"with {CODE_VALUES} select round(avg(regexp_matches(text, '[Cc]opyright')::int::double), 6) as share from files")
for _kind, _p in transform.KINDS.items():
    add(f"xform_mask_{_kind}", lambda s, d, k=_kind: docs(s, d).select("doc_id", F.md5(transform.mask(F.col("text"), (k,))).alias("h")), f"select doc_id, md5(regexp_replace(text, '{esc(_p)}', '<{_kind}>', 'g')) as h from documents")
_all = "text"
for _kind, _p in transform.KINDS.items():
    _all = f"regexp_replace({_all}, '{esc(_p)}', '<{_kind}>', 'g')"
add("xform_mask_all", lambda s, d: docs(s, d).select("doc_id", F.md5(transform.mask(F.col("text"))).alias("h")), f"select doc_id, md5({_all}) as h from documents")
add("xform_ip_valid_octets", lambda s, d: docs(s, d).select("doc_id", F.md5(F.regexp_replace("text", transform.IP_VALID, "<ip>")).alias("h")), f"select doc_id, md5(regexp_replace(text, '{transform.IP_VALID}', '<ip>', 'g')) as h from documents")
add(
    "pii_counts_by_kind", lambda s, d: docs(s, d).agg(*(F.sum(F.regexp_count("text", F.lit(p))).cast("long").alias(k) for k, p in transform.LINEAR.items())),
    "select " + ", ".join(f"sum(len(regexp_extract_all(text, '{esc(p)}')))::bigint as {k}" for k, p in transform.KINDS.items()) + " from documents",
)
add("pii_luhn", lambda s, d: docs(s, d).select("doc_id", F.explode(F.regexp_extract_all("text", F.lit("([0-9]{16})"), 1)).alias("n")).select("doc_id", "n", transform.luhn(F.col("n")).alias("ok")), "with t as (select doc_id, unnest(regexp_extract_all(text, '[0-9]{16}')) as n from documents), s as (select doc_id, n, list_sum(list_transform(range(1, 17), lambda i: case when i % 2 = 1 then case when 2 * n[i]::int > 9 then 2 * n[i]::int - 9 else 2 * n[i]::int end else n[i]::int end)) as t from t) select doc_id, n, t % 10 = 0 as ok from s")

# ---- sampling and composition
H = "(('0x' || substr(md5(file_id::varchar), 1, 8))::bigint % 2147483648)"
SHARE = {"fr": 0.445, "de": 0.135}
add("sample_budget_lang", lambda s, d: sampling.fraction_sample(files(s, d), SHARE).select("file_id", "lang"), f"with {FILES} select file_id, lang from files where {H} < case lang when 'fr' then {int(0.445 * sampling.P31)} when 'de' then {int(0.135 * sampling.P31)} else 2147483648 end")
BUDGET = {"fr": 60_000, "de": 40_000}
add(
    "sample_byte_budget", lambda s, d: sampling.budget_sample(files(s, d), BUDGET).select("file_id", "lang"),
    f"with {FILES}, t as (select lang, sum(n_bytes) as b from files group by lang) select file_id, lang from files join t using (lang) where {H} < case lang when 'fr' then floor(least(1.0::double, 60000::double / b) * 2147483648)::bigint when 'de' then floor(least(1.0::double, 40000::double / b) * 2147483648)::bigint else 2147483648 end",
)
add("sample_exact_k", lambda s, d: sampling.exact_k(files(s, d), 20).select("file_id", "lang"), f"with {FILES} select file_id, lang from files qualify row_number() over (partition by lang order by {H}, file_id) <= 20")
add("sample_running_budget", lambda s, d: sampling.running_budget(files(s, d), 100_000).select("file_id", "lang"), f"with {FILES} select file_id, lang from files qualify sum(n_bytes) over (partition by lang order by {H}, file_id rows unbounded preceding) <= 100000")
add("sample_bernoulli", lambda s, d: files(s, d).sampleBy("lang", {"en": 0.5, "fr": 0.5, "de": 0.5, "es": 0.5}, seed=5).select("file_id"))
add("ablate_star_filter", lambda s, d: files(s, d).where("stars >= 5").select("file_id", "stars"), f"with {FILES} select file_id, stars from files where stars >= 5")
add(
    "ablate_star_diversity", lambda s, d: files(s, d).select(F.when(F.col("stars") >= 5, "stars").otherwise("rest").alias("arm"), "lang", F.explode(tokens(F.col("text"))).alias("w")).groupBy("arm").agg(F.count_distinct("lang").alias("n_lang"), F.count(F.lit(1)).alias("n_tokens"), F.count_distinct("w").alias("n_words")),
    f"with {FILES} select arm, count(distinct lang)::bigint as n_lang, count(*)::bigint as n_tokens, count(distinct w)::bigint as n_words from (select case when stars >= 5 then 'stars' else 'rest' end as arm, lang, unnest({TOKENS}) as w from files) group by arm",
)
add("embed_centroid_dispersion", lambda s, d: sampling.centroid_dispersion(table(s, d, "embeddings")), "select label, max(n)::bigint as n, round(sum(s - m * m), 4) as dispersion from (select label, i, count(*) as n, avg(x) as m, avg(x * x) as s from (select label, unnest(range(64)) as i, unnest(embedding)::double as x from embeddings) group by label, i) group by label")
add("embed_covariance", lambda s, d: sampling.covariance(table(s, d, "embeddings"), 8), "select i::int as i, j::int as j, round(avg(embedding[i+1]::double * embedding[j+1]::double) - avg(embedding[i+1]::double) * avg(embedding[j+1]::double), 4) as cov from embeddings, range(8) a(i), range(8) b(j) where j >= i group by 1, 2")
add("embed_pca_outliers", lambda s, d: sampling.pca_outliers(table(s, d, "embeddings")))
add(
    "lowquality_pattern_counts", lambda s, d: docs(s, d).agg(*(F.sum(c.cast("long")).alias(n) for n, c in {"too_short": F.length("text") < 50, "symbols": F.col("text").rlike("[#%&*$]{3}"), "hex": F.col("text").rlike("[0-9a-f]{32}")}.items())),
    "select sum((length(text) < 50)::int)::bigint as too_short, sum(regexp_matches(text, '[#%&*$]{3}')::int)::bigint as symbols, sum(regexp_matches(text, '[0-9a-f]{32}')::int)::bigint as hex from documents",
)
both("corpus_lang_distribution", "select lang, count(*) as n_files, cast(sum(n_chars) as bigint) as n_chars, round(cast(sum(n_chars) as double) / sum(sum(n_chars)) over (), 6) as share from {documents} group by lang")
CATEGORY = "select 'raw' as category, source, len(w)::bigint as n_tokens from (select source, {t} as w from documents) union all select 'web', 'pages', len(w)::bigint from (select {p} as w from pages) union all select 'dialogue', role, len(w)::bigint from (select role, {t} as w from conversations)".format(t=TOKENS, p=TOKENS.replace("text", "html"))


def parts(s, d):
    n = lambda c: F.size(tokens(F.col(c))).cast("long").alias("n_tokens")
    return docs(s, d).select(F.lit("raw").alias("category"), "source", n("text")).union(table(s, d, "pages").select(F.lit("web"), F.lit("pages"), n("html"))).union(table(s, d, "conversations").select(F.lit("dialogue"), "role", n("text")))


add("corpus_composition", lambda s, d: sampling.composition(parts(s, d)), f"with p as ({CATEGORY}) select category, source, sum(n_tokens)::bigint as n_tokens, round(100.0::double * sum(n_tokens) / (select sum(n_tokens) from p), 4) as share from p group by rollup (category, source)")
add("corpus_token_counts", lambda s, d: docs(s, d).select("doc_id", F.size(tokens(F.col("text"))).cast("long").alias("n_words"), F.octet_length("text").cast("long").alias("n_bytes")), f"select doc_id, len({TOKENS})::bigint as n_words, octet_length(encode(text))::bigint as n_bytes from documents")
add(  # the corpus before and after exact deduplication: how far does removal move its languages
    "corpus_compare", lambda s, d: sampling.divergence(docs(s, d), dedup.exact_dedup(files(s, d)), "lang"),
    "with p as (select lang, count(*)::double / sum(count(*)) over () as p from documents group by lang), once as (select lang from documents qualify row_number() over (partition by sha256(text) order by (doc_id * 37 + 11) % 7 desc, 19691 - (4 - (doc_id * 53) % 5) desc, doc_id) = 1), q as (select lang, count(*)::double / sum(count(*)) over () as q from once group by lang), j as (select coalesce(p, 0) as p, coalesce(q, 0) as q from p full join q using (lang)) select round(sum(case when p > 0 then p * log2(2 * p / (p + q)) else 0 end + case when q > 0 then q * log2(2 * q / (p + q)) else 0 end) / 2, 6) as js, round(sum(abs(p - q)) / 2, 6) as tv from j",
)

# ---- annealing
KEY = "(lower(text) like '%that it%' or lower(text) like '%of the%')"
keyed = lambda df: df.where(F.lower("text").contains("that it") | F.lower("text").contains("of the"))
add("anneal_keyword_subset", lambda s, d: keyed(files(s, d)).where(sampling.unit_hash(F.col("file_id")) < sampling.P31 // 2).select("file_id"), f"with {FILES} select file_id from files where {KEY} and {H} < 1073741824")
MIX = {"original": 84, "algorithmic": 12, "synthetic": 4}
add(
    "anneal_mixture", lambda s, d: keyed(files(s, d)).select(F.lit("algorithmic").alias("part"), "file_id", "n_bytes").union(files(s, d).select(F.lit("original"), "file_id", "n_bytes")).withColumn("run", F.sum("n_bytes").over(Window.partitionBy("part").orderBy(sampling.unit_hash(F.col("file_id")), "file_id").rowsBetween(Window.unboundedPreceding, 0))).where(F.col("run") <= F.when(F.col("part") == "original", 840_000).otherwise(124_400)).select("part", "file_id"),
    f"with {FILES}, u as (select 'algorithmic' as part, * from files where {KEY} union all select 'original', * from files) select part, file_id from u qualify sum(n_bytes) over (partition by part order by {H}, file_id rows unbounded preceding) <= case part when 'original' then 840000 else 124400 end",
)
#: Words of each category and source of the tables: all documents, those with words of prose that stand in for keywords, and synthetic turns.
T3 = f"""(select category, source, cast(sum(length(text) - length(replace(text, ' ', '')) + 1) as bigint) as tokens from (select 'original' as category, source, text from {{documents}}
 union all select 'algorithmic', source, text from {{documents}} where {KEY} union all select 'synthetic', role, text from {{conversations}}) u group by category, source)"""
both("anneal_mixture_table", f"select category, source, cast(tokens as double) as tokens, round(cast(100 * tokens / sum(tokens) over () as double), 2) as share from {T3} t")
both("ablate_anneal_without_hq", f"select category, cast(sum(tokens) as double) as tokens from {T3} t where category = 'original' group by category")
add("anneal_distribution_shift", lambda s, d: sampling.divergence(files(s, d), keyed(files(s, d)), "lang").select("tv"), f"with {FILES}, p as (select lang, count(*)::double / sum(count(*)) over () as p from files group by lang), q as (select lang, count(*)::double / sum(count(*)) over () as q from files where {KEY} group by lang) select round(sum(abs(coalesce(p, 0) - coalesce(q, 0))) / 2, 6) as tv from p full join q using (lang)")
both("synth_textbook_prompts", "select doc_id, concat('Explain step by step, as a textbook would: ', text) as prompt from {documents}")

# ---- tuning data
both("sft_pairs", "select conv_id, turn, text as instruction, response from (select conv_id, turn, role, text, lead(role) over (partition by conv_id order by turn) as r, lead(text) over (partition by conv_id order by turn) as response from {conversations}) q where role = 'user' and r = 'assistant'")
both("sft_clean_dialogues", "select conv_id from {conversations} group by conv_id having sum(case when role = 'assistant' then 1 else 0 end) > 0 and count(*) = max(turn) + 1 and min(length(text)) > 0")
both("sft_first_user_query", "select conv_id, turn, text from (select conv_id, turn, text, row_number() over (partition by conv_id order by turn) as r from {conversations} where role = 'user') q where r = 1")
both("sft_code_related_turns", "select conv_id, turn from {conversations} where lower(text) like '%code%' or lower(text) like '%function%' or lower(text) like '%that%'")
both("sft_regenerate_queue", "select conv_id, turn, length(text) as n from {conversations} where role = 'assistant' and length(text) < 40")
add("sft_language_ratio", lambda s, d: sampling.exact_k(files(s, d), 10).groupBy("lang").agg(F.count(F.lit(1)).alias("n")), f"with {FILES} select lang, least(count(*), 10)::bigint as n from files group by lang")
both("sft_seed_topk", "select lang, doc_id from (select d.lang, d.doc_id, row_number() over (partition by d.lang order by l.quality desc, d.n_chars desc, d.doc_id) as r from {documents} d join {labels} l on d.doc_id = l.doc_id) q where r <= 5")
both("sft_task_grid", "select l.lang, k.level, t.task, concat('Write a ', t.task, ' task in ', l.lang, ', level ', k.level) as prompt from (values ('Python'), ('Java'), ('Go')) l(lang) cross join (values ('easy'), ('medium'), ('hard')) k(level) cross join (values ('algorithm'), ('debugging'), ('explanation')) t(task)")
both("sft_prompts", "select doc_id, concat('Language: ', lang, '. Use this text: ', text) as prompt from {documents}")
both("sft_stage_composition", "select stage, cast(sum(n) as bigint) as n from (values (1, 700000), (1, 2300000), (1, 1000000), (2, 36000), (2, 111000), (2, 110000), (2, 110000)) t(stage, n) group by stage")
both("sft_stage1_only", "select conv_id, turn from {conversations} where not (lower(text) like '%code%' or lower(text) like '%function%' or lower(text) like '%that%')")
both("sft_mixed_shuffle", "select conv_id, turn, row_number() over (order by md5(concat(cast(conv_id as string), '-', cast(turn as string)))) as place from {conversations}".replace("as string", "as varchar(20)"))
both("sft_dedup", "select min(conv_id * 1000 + turn) as id, count(*) as n from {conversations} group by md5(text)")
API = "(values ('json', 'loads', false), ('json', 'dumps', false), ('os', 'getcwdu', true), ('re', 'compile', false), ('re', 'template', true)) a(module, symbol, deprecated)"
both("sft_package_prompts", f"select module, symbol, concat('Show how to use ', module, '.', symbol) as prompt from {API} where not deprecated")
both("sft_stale_calls", f"select c.call, coalesce(a.deprecated, true) as stale from (values ('loads'), ('getcwdu'), ('nothing')) c(call) left join {API} on a.symbol = c.call where coalesce(a.deprecated, true)")
both("sft_useful_sentences", "select page_id, length(html) as n from {pages} where length(html) > 1000")
