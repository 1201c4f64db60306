"""Ingest, deduplication and decontamination workloads."""

from __future__ import annotations

from pyspark.sql import functions as F

from corpusmill.operators import decontam, dedup, ingest, minhash
from corpusmill.operators.components import components
from corpusmill.plans.durable import settled
from corpusmill.schema import FILES, TOKENS, files, table
from corpusmill.workloads.catalog import add

# ---- ingest
add("prep_size_gate", lambda s, d: ingest.size_gate(files(s, d), 8000).select("file_id", "n_bytes"), f"with {FILES} select file_id, n_bytes from files where n_bytes <= 8000")
add("prep_language_gate", lambda s, d: ingest.language_gate(files(s, d), ingest.registry(s)).select("file_id", "ext", "language"), f"with {FILES}, reg(ext, language) as (values {ingest.registry_values()}) select file_id, files.ext, language from files join reg using (ext)")
add(
    "prep_prune_languages", lambda s, d: ingest.prune_languages(files(s, d), table(s, d, "labels"), 200_000, 0.8).select("file_id", "lang"),
    f"with {FILES}, k as (select lang from files left join labels on file_id = labels.doc_id group by lang having sum(n_bytes) >= 200000 and coalesce(avg(quality::double), 0) >= 0.8) select file_id, lang from files where lang in (select lang from k)",
)
add(
    "prep_notebook_cells", lambda s, d: ingest.notebook_cells(ingest.notebooks(table(s, d, "conversations"))),
    "select conv_id::varchar || '.ipynb' as path, coalesce(string_agg(coalesce(text, ''), chr(10) || chr(10) order by turn, text) filter (role = 'assistant'), '') as code, (count(*) filter (role = 'assistant'))::int as n_cells from conversations group by conv_id",
)
add(
    "prep_merge_sources", lambda s, d: ingest.merge_sources(documents=table(s, d, "documents").select(F.col("doc_id").alias("id"), "text"), pages=table(s, d, "pages").select(F.col("page_id").alias("id"), F.col("html").alias("text"), "url")).select("origin", "id", "url", F.length("text").cast("long").alias("n")),
    "select 'documents' as origin, doc_id as id, null::varchar as url, length(text)::bigint as n from documents union all select 'pages', page_id, url, length(html)::bigint from pages",
)

# ---- exact, repository and chunk level
KEEP = "keep as (select file_id from (select file_id, row_number() over (partition by sha256(text) order by stars desc, commit_day desc, file_id) as r from files) where r = 1)"
add("dedup_exact_best", lambda s, d: dedup.exact_dedup(files(s, d)).select("file_id", "stars"), f"with {FILES}, {KEEP} select file_id, stars from files where file_id in (select file_id from keep)")
add("dedup_exact_window", lambda s, d: dedup.exact_dedup_window(files(s, d)).select("file_id", "stars"), f"with {FILES}, {KEEP} select file_id, stars from files where file_id in (select file_id from keep)")
add("dedup_exact_folded", lambda s, d: dedup.exact_dedup(files(s, d), fold=True).select("file_id"), rf"with {FILES} select file_id from (select file_id, row_number() over (partition by trim(regexp_replace(lower(text), '\s+', ' ', 'g')) order by stars desc, commit_day desc, file_id) as r from files) where r = 1")
add("dedup_share_exact", lambda s, d: files(s, d).agg(F.round(1 - F.count_distinct(F.sha2("text", 256)) / F.count(F.lit(1)), 6).alias("share")), "select round(1 - count(distinct sha256(text))::double / count(*), 6) as share from documents")
add("dedup_share_approx", lambda s, d: files(s, d).agg(F.round(1 - F.approx_count_distinct(F.sha2("text", 256), 0.01) / F.count(F.lit(1)), 2).alias("share")))
REPO = f"""t as (select repo, stars, commit_day, sha256(text) as d, len({TOKENS}) as t from files),
r as (select repo, sha256(string_agg(d, ',' order by d)) as key, max(stars) as stars, max(commit_day) as commit_day, sum(t)::bigint as n_tokens from t group by repo),
rk as (select repo, n_tokens from (select *, row_number() over (partition by key order by stars desc, commit_day desc, repo) as n from r) where n = 1)"""
add("dedup_repo_exact", lambda s, d: dedup.repo_keepers(files(s, d)), f"with {FILES}, {REPO} select repo from rk")
add("dedup_repo_concat", lambda s, d: dedup.repo_concat_keys(files(s, d)), f"with {FILES} select repo, sha256(string_agg(text, chr(10) order by file_id)) as key, count(*)::bigint as n_files from files group by repo")
add(
    "dedup_residual_after_repo", lambda s, d: dedup.exact_dedup(dedup.repo_dedup(files(s, d))).agg(F.count(F.lit(1)).alias("n_files"), F.sum("n_bytes").alias("n_bytes")),
    f"with {FILES}, {REPO}, l as (select * from files where repo in (select repo from rk)) select count(*)::bigint as n_files, sum(n_bytes)::bigint as n_bytes from (select n_bytes, row_number() over (partition by sha256(text) order by stars desc, commit_day desc, file_id) as r from l) where r = 1",
)
add("dedup_charwise_equal_tokens", lambda s, d: dedup.equal_token_volume(dedup.repo_dedup(files(s, d))), f"with {FILES}, {REPO}, g as (select count(*) as n, sum(len({TOKENS})) as t from files where repo in (select repo from rk) group by sha256(text)) select sum(case when n > 1 then t else 0 end)::bigint as equal_tokens, sum(t)::bigint as all_tokens from g")
CHUNK = """first as (select c, min((file_id, pos)) as f from ch where length(c) > 10 group by c)
select file_id, count(*)::bigint as n_chunks, sum((f is null or f = (file_id, pos))::int)::bigint as n_kept, sum(case when f is null or f = (file_id, pos) then length(ch.c) else 0 end)::bigint as kept_chars from ch left join first on ch.c = first.c group by file_id"""
add("dedup_chunk_lines", lambda s, d: dedup.chunk_dedup(files(s, d)), f"with ch as (select doc_id as file_id, unnest(range(len(l)))::int as pos, unnest(l) as c from (select doc_id, string_split(text, chr(10)) as l from documents)), {CHUNK}")
add("dedup_chunk_fixed", lambda s, d: dedup.chunk_dedup(files(s, d), "fixed", 400), f"with ch as (select doc_id as file_id, i::int as pos, substring(text, (i * 400 + 1)::int, 400) as c from (select doc_id, text, unnest(range(greatest(ceil(length(text) / 400.0)::bigint, 1))) as i from documents)), {CHUNK}")
add(
    "dedup_level_report", lambda s, d: dedup.level_report(files(s, d)),
    f"""with {FILES}, {REPO}, {KEEP}, tk as (select file_id, repo, len({TOKENS}) as t from files), tot as (select count(*) as n, sum(t) as t from tk),
l as (select * from files where repo in (select repo from rk)), lk as (select file_id from (select file_id, row_number() over (partition by sha256(text) order by stars desc, commit_day desc, file_id) as r from l) where r = 1)
select 'file' as level, (select n from tot)::bigint as rows_in, count(*)::bigint as rows_kept, sum(t)::bigint as tokens_kept, round(100.0::double * sum(t) / (select t from tot), 4) as token_share from tk where file_id in (select file_id from keep)
union all select 'repository', (select count(distinct repo) from files)::bigint, (select count(*) from rk)::bigint, sum(t)::bigint, round(100.0::double * sum(t) / (select t from tot), 4) from tk where repo in (select repo from rk)
union all select 'repository_then_file', (select count(*) from l)::bigint, count(*)::bigint, sum(t)::bigint, round(100.0::double * sum(t) / (select t from tot), 4) from tk where file_id in (select file_id from lk)""",
)
add(
    "dedup_incremental", lambda s, d: dedup.against_index(files(s, d).where("file_id % 2 = 0").select(dedup.digest(F.col("text")).alias("digest")), files(s, d).where("file_id % 2 = 1")).select("file_id"),
    f"with {FILES}, b as (select * from files where file_id % 2 = 1), x as (select sha256(text) as h from files where file_id % 2 = 0) select file_id from (select file_id, sha256(text) as h, row_number() over (partition by sha256(text) order by stars desc, commit_day desc, file_id) as r from b) where r = 1 and h not in (select h from x)",
)

# ---- fuzzy
GRAMS = f"""tk as (select doc_id as file_id, {TOKENS} as w from documents),
g as (select file_id, list_distinct(case when len(w) < 5 then [array_to_string(w, ' ')] else list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' ')) end) as grams from tk where len(w) > 0)"""
add(
    "fuzzy_shingle_counts", lambda s, d: table(s, d, "documents").select("doc_id", F.size(minhash.shingles(F.col("text"), 5)).cast("long").alias("n_word"), F.size(minhash.shingles(F.col("text"), 5, "char")).cast("long").alias("n_char")),
    f"""with {GRAMS}, c as (select doc_id, len(list_distinct(case when length(text) = 0 then [] when length(text) < 5 then [lower(text)] else list_transform(range(1, length(lower(text)) - 3), lambda i: substring(lower(text), i::int, 5)) end))::bigint as n_char from documents)
select doc_id, coalesce(len(grams), 0)::bigint as n_word, n_char from c left join g on doc_id = file_id""",
)
_A, _C = minhash.constants(16)
SIG = f"""{GRAMS}, x as (select file_id, list_transform(grams, lambda q: ('0x' || substr(md5(q), 1, 8))::bigint % {minhash.P}) as x from g),
sig as (select file_id, [{", ".join(f"list_min(list_transform(x, lambda h: (h * {a} + {c}) % {minhash.P}))" for a, c in zip(_A, _C))}] as sig from x)"""
BANDS = f"{SIG}, bands as (select file_id, b::int as band, md5(array_to_string(sig[b*2+1:b*2+2], '-')) as key from sig, range(8) r(b))"
EDGES = f"{BANDS}, least as (select band, key, min(file_id) as b from bands group by band, key having count(*) > 1), edges as (select distinct file_id as a, b from bands join least using (band, key) where file_id <> b)"
COMP = f"""{EDGES}, und as (select a, b from edges union select b, a from edges), walk(node, root) as (select a, a from und union select walk.node, und.b from walk join und on walk.root = und.a),
comp as (select node, min(root) as root from walk group by node)"""
small = lambda s, d: minhash.signatures(files(s, d), 16)
add("minhash_signature_small", lambda s, d: small(s, d).select("file_id", F.md5(F.concat_ws(",", F.transform("sig", lambda x: x.cast("string")))).alias("sig_md5")), f"with {SIG} select file_id, md5(array_to_string(sig, ',')) as sig_md5 from sig")
add("lsh_band_buckets", lambda s, d: minhash.bands(small(s, d), 8, 2).groupBy("band", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), f"with {BANDS} select band, key, count(*)::bigint as n from bands group by band, key having count(*) > 1")
add("lsh_candidate_edges", lambda s, d: minhash.bucket_edges(minhash.bands(small(s, d), 8, 2)), f"with {EDGES} select a, b from edges")
add("lsh_components", lambda s, d: components(minhash.bucket_edges(minhash.bands(small(s, d), 8, 2))), f"with recursive {COMP} select node, root from comp")
add(
    "dedup_fuzzy_keep_best", lambda s, d: minhash.keep_best(files(s, d), components(minhash.bucket_edges(minhash.bands(small(s, d), 8, 2)))).select("file_id"),
    f"with recursive {FILES}, {COMP}, rk as (select file_id, row_number() over (partition by root order by stars desc, commit_day desc, file_id) as r from files join comp on node = file_id) select file_id from files where file_id not in (select file_id from rk where r > 1)",
)
PAIRS = f"{GRAMS}, e as (select file_id, unnest(grams) as gram, len(grams) as m from g), inter as (select x.file_id as a, y.file_id as b, x.m as ma, y.m as mb, count(*) as inter from e x join e y on x.gram = y.gram and x.file_id < y.file_id group by 1, 2, 3, 4)"
add("jaccard_bruteforce_pairs", lambda s, d: minhash.shared_gram_pairs(files(s, d), 70).select("a", "b", F.col("inter").cast("long").alias("inter"), F.col("uni").cast("long").alias("uni")), f"with {PAIRS} select a, b, inter::bigint as inter, (ma + mb - inter)::bigint as uni from inter where 100 * inter >= 70 * (ma + mb - inter)")
add("jaccard_verified_pairs", lambda s, d: minhash.verify_edges(minhash.bucket_edges(minhash.bands(small(s, d), 8, 2)), files(s, d), 70).select("a", "b"), f"with {EDGES}, e as (select file_id, unnest(grams) as gram, len(grams) as m from g), v as (select a, b, x.m as ma, y.m as mb, count(*) as inter from edges join e x on x.file_id = a join e y on y.file_id = b and x.gram = y.gram group by 1, 2, 3, 4) select a, b from v where 100 * inter >= 70 * (ma + mb - inter)")


def estimate_error(s, d):
    """Similarity by signature agreement against the exact one, for exact pairs of .7 or more."""
    pairs = settled(minhash.shared_gram_pairs(files(s, d), 70))
    needed = pairs.select(F.col("a").alias("file_id")).union(pairs.select("b")).distinct()
    sig = settled(minhash.signatures(files(s, d).join(needed, "file_id", "left_semi"), 64))
    both_ = pairs.join(sig.toDF("a", "sa"), "a").join(sig.toDF("b", "sb"), "b")
    agree = F.aggregate(F.zip_with("sa", "sb", lambda x, y: (x == y).cast("int")), F.lit(0), lambda p, q: p + q) / 64.0
    return both_.select("a", "b", F.round(F.col("inter") / F.col("uni"), 6).alias("exact"), F.round(agree, 6).alias("estimate"))


add("minhash_estimate_error", estimate_error)
add("lsh_s_curve", lambda s, d: minhash.curve(table(s, d, "lineitem").select((F.col("l_quantity").cast("double") / 51).alias("s")).distinct(), [(16, 128), (32, 64), (64, 32), (128, 16), (256, 8)]), "select b::int as bands, r::int as rows, round(s, 6) as s, round(1 - pow(1 - pow(s, r), b), 6) as p, round(pow(1.0::double / b, 1.0::double / r), 6) as knee from (values (16,128),(32,64),(64,32),(128,16),(256,8)) t(b, r), (select distinct l_quantity::double / 51 as s from lineitem) q")
add("dedup_fuzzy_best", lambda s, d: minhash.fuzzy_dedup(files(s, d)).select("file_id"))
add("dedup_pipeline_file", lambda s, d: minhash.fuzzy_dedup(dedup.exact_dedup(files(s, d))).select("file_id"))
add("dedup_pipeline_verified", lambda s, d: minhash.fuzzy_dedup(dedup.exact_dedup(files(s, d)), b=256, r=8, verify=70).select("file_id"))
add("dedup_repo_fuzzy", lambda s, d: minhash.repo_fuzzy(files(s, d)))


# comparator: the pairs of the library's MinHash similarity join at distance .3 or less, between classes of equal files, with the copies of each
add("baseline_minhash_ml", lambda s, d: minhash.ml_pairs(files(s, d), 70))

# ---- decontamination of tuning data
W10 = f"bw as (select item_id, {TOKENS} as w from benchmark), bg as (select distinct item_id, array_to_string(w[i:i+9], ' ') as gram from (select item_id, w, unnest(range(1, len(w) - 8)) as i from bw where len(w) >= 10))"


def grams_of(source: str) -> str:
    return f"dw as (select id, {TOKENS} as w from ({source})), dg as (select distinct id, array_to_string(w[i:i+9], ' ') as gram from (select id, w, unnest(range(1, len(w) - 8)) as i from dw where len(w) >= 10))"


DOCS, PAGES, TURNS = "select doc_id as id, text from documents", r"select page_id as id, regexp_replace(html, '<[^>]*>', ' ', 'g') as text from pages", "select conv_id * 1000 + turn as id, text from conversations"
parts = {
    "decontam_10gram": (lambda s, d: table(s, d, "documents").select(F.col("doc_id").alias("id"), "text"), DOCS),
    "decontam_10gram_pages": (lambda s, d: table(s, d, "pages").select(F.col("page_id").alias("id"), F.regexp_replace("html", "<[^>]*>", " ").alias("text")), PAGES),
    "decontam_10gram_turns": (lambda s, d: table(s, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text"), TURNS),
}
for name, (rows, sql) in parts.items():
    add(name, lambda s, d, rows=rows: decontam.drop_ngram_overlap(rows(s, d), table(s, d, "benchmark")).select("id"), f"with {W10}, {grams_of(sql)} select id from dw where id not in (select id from dg join bg using (gram))")
docs = parts["decontam_10gram"][0]
add("decontam_report", lambda s, d: decontam.overlap_report(docs(s, d), table(s, d, "benchmark")), f"with {W10}, {grams_of(DOCS)} select id, item_id, count(*)::bigint as n_shared from dg join bg using (gram) group by id, item_id")
add("decontam_n_sweep", lambda s, d: decontam.sweep(docs(s, d), table(s, d, "benchmark"), [8, 10, 13]), " union all ".join(f"select {n} as n, count(distinct id)::bigint as n_docs from (with {W10.replace('i+9', f'i+{n - 1}').replace('- 8', f'- {n - 2}').replace('>= 10', f'>= {n}')}, {grams_of(DOCS).replace('i+9', f'i+{n - 1}').replace('- 8', f'- {n - 2}').replace('>= 10', f'>= {n}')} select id from dg join bg using (gram))" for n in (8, 10, 13)))
ENTRY = f"ep as (select distinct list_sort(list_filter(w, lambda x: length(x) = list_max(list_transform(w, lambda y: length(y)))))[1] as word from (select {TOKENS} as w from benchmark) where len(w) > 0)"
add("decontam_entry_point", lambda s, d: decontam.drop_entry_points(docs(s, d), table(s, d, "benchmark")).select("id"), f"with {ENTRY}, dw as (select doc_id as id, {TOKENS} as w from documents) select id from dw where not exists (select 1 from ep where list_contains(w, word))")
add("decontam_all", lambda s, d: decontam.decontaminate(docs(s, d), table(s, d, "benchmark")).select("id"), f"with {ENTRY}, {W10}, {grams_of(DOCS)} select id from dw where not exists (select 1 from ep where list_contains(w, word)) and id not in (select id from dg join bg using (gram))")
