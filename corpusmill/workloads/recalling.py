"""Web recall workloads; the target is the quality label."""

from __future__ import annotations

from pyspark.sql import functions as F

from corpusmill.functions.surface import bpe_encode
from corpusmill.operators import classifier, recall
from corpusmill.operators.sampling import unit_hash
from corpusmill.schema import TOKENS, table, tokens
from corpusmill.workloads.catalog import add, both

HOST = r"regexp_replace(regexp_extract(url, '^[a-z]+://([^/?#]+)', 1), '^(www|m)\.', '')"
MODEL = f"""tw as (select quality as y, unnest({TOKENS}) as w from documents join labels using (doc_id)), cw as (select w, sum(y) as p, sum(1 - y) as q from tw group by w),
tt as (select sum(p) as tp, sum(q) as tq, count(*) as v from cw), model as (select w, ln((p + 1.0::double) / (tp + v)) - ln((q + 1.0::double) / (tq + v)) as odds from cw, tt),
pw as (select id, w, count(*) as c from (select page_id as id, unnest({TOKENS.replace('text', 'html')}) as w from pages) group by id, w), sc as (select id, round(sum(c * odds) / sum(c), 6) as score from pw join model using (w) group by id)"""
seed = lambda s, d: table(s, d, "documents").join(table(s, d, "labels"), "doc_id").select("text", F.col("quality").alias("y"))
pages = lambda s, d: table(s, d, "pages").select(F.col("page_id").alias("id"), "url", F.col("html").alias("text"))
scored = lambda s, d: recall.score(pages(s, d), recall.train(seed(s, d)))
hits = lambda s, d: scored(s, d).where("score > 0.2")
both("recall_seed_set", "select d.doc_id, l.quality as y from {documents} d join {labels} l on d.doc_id = l.doc_id")
add("recall_logodds_scores", scored, f"with {MODEL} select id, score from sc")
add("recall_hits", lambda s, d: hits(s, d).select("id"), f"with {MODEL} select id from sc where score > 0.2")
DOM = f"dom as (select {HOST} as host, count(*)::bigint as n_pages, count(s.id)::bigint as n_hits from pages left join (select id from sc where score > 0.2) s on page_id = s.id group by 1 having count(s.id) > count(*) * 0.1)"
add("recall_domains", lambda s, d: recall.discover(pages(s, d), hits(s, d)).select("host", "n_pages", F.col("n_hits").cast("long").alias("n_hits")), f"with {MODEL}, {DOM} select * from dom")
add("recall_domains_minpages", lambda s, d: recall.discover(pages(s, d), hits(s, d), min_pages=3).select("host"), f"with {MODEL}, {DOM} select host from dom where n_pages >= 3")
add("recall_url_prefix_recovered", lambda s, d: recall.expand(pages(s, d), hits(s, d), recall.discover(pages(s, d), hits(s, d)), ["/en", "/de"]).select("id"), rf"with {MODEL}, {DOM} select page_id as id from pages where regexp_matches(regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1), '^(/en|/de)(/|$)') and {HOST} in (select host from dom) and page_id not in (select id from sc where score > 0.2)")
both("recall_prefix_candidates", "select regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) as host, regexp_extract(url, '^[a-z]+://[^/?#]+/([^/?#]*)', 1) as prefix, count(*) as n from {pages} group by 1, 2")
seeded = lambda s, d: table(s, d, "documents").join(table(s, d, "labels"), "doc_id").select(F.col("doc_id").alias("id"), "text", F.col("quality").alias("y"))
plain_pages = lambda s, d: table(s, d, "pages").select(F.col("page_id").alias("id"), "url", recall.page_text(F.col("html")).alias("text"))
add("recall_round_history", lambda s, d: recall.loop(plain_pages(s, d), seeded(s, d), ["/en", "/de"], cut=0.9))
add("recall_scores", lambda s, d: recall.averaged(seeded(s, d))(plain_pages(s, d)))

# ---- reports on a held-out fifth, drawn by the hash of the id
FOLD = "(('0x' || substr(md5(doc_id::varchar), 1, 8))::bigint % 2147483648) % 5 = 0"
CUTS = [0.1, 0.3, 0.5, 0.7, 0.9]


def held_out(s, d, fit):
    rows = seeded(s, d).withColumn("out", unit_hash(F.col("id")) % 5 == 0)
    return fit(rows.where("not out"))(rows.where("out")).join(rows.where("out").select("id", "y"), "id")


add("recall_classifier_report", lambda s, d: classifier.report(held_out(s, d, recall.averaged), CUTS))
ODDS_CUTS = [-0.5, 0.0, 0.5, 1.0]
add(
    "recall_logodds_report", lambda s, d: classifier.report(held_out(s, d, recall.log_odds), ODDS_CUTS),
    f"""with sd as (select doc_id, text, quality as y, {FOLD} as held from documents join labels using (doc_id)), tw as (select y, unnest({TOKENS}) as w from sd where not held), cw as (select w, sum(y) as p, sum(1 - y) as q from tw group by w),
tt as (select sum(p) as tp, sum(q) as tq, count(*) as v from cw), model as (select w, ln((p + 1.0::double) / (tp + v)) - ln((q + 1.0::double) / (tq + v)) as odds from cw, tt),
pw as (select doc_id, w, count(*) as c from (select doc_id, unnest({TOKENS}) as w from sd where held) group by 1, 2), sc as (select doc_id, round(round(sum(c * odds) / sum(c), 6), 3) as score from pw join model using (w) group by 1),
r as (select score, y from sc join labels l using (doc_id) join sd using (doc_id)), auc as (select round(sum(case when a.score > b.score then 1::double when a.score = b.score then 0.5::double else 0 end) / count(*), 6) as auc from r a, r b where a.y = 1 and b.y = 0)
select cut, n_out, case when n_out > 0 then round(hit::double / n_out, 6) end as precision, round(hit::double / all_p, 6) as recall, round(2.0::double * hit / (n_out + all_p), 6) as f1, auc from (select cut, sum((score > cut)::int)::bigint as n_out, sum((score > cut)::int * y) as hit, sum(y) as all_p from r, (values {", ".join(f"({c}::double)" for c in ODDS_CUTS)}) g(cut) group by cut), auc""",
)

# ---- the same recall over other corpora, a second classifier for text in code hosting, and topics of domains
corpora = lambda s, d: {"documents": table(s, d, "documents").select(F.col("doc_id").alias("id"), "text"), "pages": pages(s, d).select("id", "text"), "conversations": table(s, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text")}
MANY = " union all ".join(f"select '{origin}' as origin, {key} as id, unnest({words}) as w from {origin}" for origin, key, words in (("documents", "doc_id", TOKENS), ("pages", "page_id", TOKENS.replace("text", "html")), ("conversations", "conv_id * 1000 + turn", TOKENS)))
add(
    "recall_multi_corpus", lambda s, d: recall.recall_many(corpora(s, d), recall.log_odds(seed(s, d)), 0.2),
    f"with {MODEL.split('pw as')[0].rstrip().rstrip(',')}, mw as (select origin, id, w, count(*) as c from ({MANY}) group by all) select origin, id from mw join model using (w) group by origin, id having round(sum(c * odds) / sum(c), 6) > 0.2",
)
add("recall_text_files", lambda s, d: recall.recall_many({"code hosting": table(s, d, "documents").where("source is not null").select(F.col("doc_id").alias("id"), "text")}, recall.averaged(seeded(s, d).withColumn("y", F.col("y")), classifier.Settings(pairs=False, seed=2)), 0.9))
TOPICS = "(values ('/en', 'code'), ('/de', 'mathematics'), ('/fr', 'code'), ('/es', 'mathematics')) t(prefix, topic)"
both("recall_domain_topics", "select p.page_id, t.topic from {pages} p join " + TOPICS + " on regexp_extract(p.url, '^[a-z]+://[^/?#]+(/[^/?#]*)', 1) = t.prefix")

# ---- segmentation by a public vocabulary
add("bpe_encode", lambda s, d: table(s, d, "documents").select("doc_id", bpe_encode("text").alias("ids")).select("doc_id", F.size("ids").cast("long").alias("n_tokens"), F.md5(F.array_join(F.col("ids").cast("array<string>"), " ")).alias("ids_md5")))
add("corpus_bpe_tokens", lambda s, d: table(s, d, "documents").select("source", F.size(bpe_encode("text")).cast("long").alias("n")).groupBy("source").agg(F.sum("n").alias("n_tokens"), F.count(F.lit(1)).alias("n_files")))
add("page_canonical_url", lambda s, d: pages(s, d).select("id", recall.canonical_url(F.col("url")).alias("canonical"), recall.base_host(F.col("url")).alias("host")), rf"select page_id as id, regexp_replace(regexp_replace(regexp_replace(regexp_replace(url, '^[a-z]+://', ''), '[?#].*$', ''), '\.html$', ''), '/+$', '') as canonical, {HOST} as host from pages")
add("page_text_extract", lambda s, d: pages(s, d).select("id", F.md5(recall.page_text(F.col("text"))).alias("h")), r"select page_id as id, md5(trim(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<(script|style|nav)[^>]*>.*?</(script|style|nav)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '\s+', ' ', 'g'))) as h from pages")
add("bpe_word_counts", lambda s, d: table(s, d, "documents").select(F.explode(tokens(F.col("text"))).alias("w")).groupBy("w").agg(F.count(F.lit(1)).alias("n")), f"select w, count(*)::bigint as n from (select unnest({TOKENS}) as w from documents) group by w")
add(
    "bpe_pair_counts_round1", lambda s, d: table(s, d, "documents").select(F.explode(tokens(F.col("text"))).alias("w")).groupBy("w").agg(F.count(F.lit(1)).alias("n")).where("length(w) > 1").select("n", F.explode(F.expr("transform(sequence(1, length(w) - 1), i -> substring(w, i, 2))")).alias("pair")).groupBy("pair").agg(F.sum("n").alias("n")),
    f"select pair, sum(n)::bigint as n from (select n, unnest(list_transform(range(1, length(w)), lambda i: substring(w, i::int, 2))) as pair from (select w, count(*) as n from (select unnest({TOKENS}) as w from documents) group by w) where length(w) > 1) group by pair",
)
