"""Annealing subsets by keyword, verified synthesis, sentence selection and the API catalogue."""

from __future__ import annotations

from pyspark.sql import functions as F

from corpusmill.functions.surface import ApiCatalogue
from corpusmill.operators import recall, sampling, snippets
from corpusmill.schema import FILES, files, table
from corpusmill.workloads.catalog import add


#: The keywords that mark algorithmic files.
KEYWORDS = ("leetcode", "def solution", "class solution")
_hit = " or ".join(f"contains(lower(text), '{k}')" for k in KEYWORDS)
#: Words of prose that stand in for the keywords on turns of conversations.
WORDS = ("that it", "of the")
_said = " or ".join(f"contains(lower(text), '{k}')" for k in WORDS)
turns = lambda s, d: table(s, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("file_id"), "text")
add("anneal_algorithmic_files", lambda s, d: snippets.keyword_subset(turns(s, d), WORDS).select("file_id"), f"select conv_id * 1000 + turn as file_id from conversations where {_said}")
add("anneal_algorithmic_documents", lambda s, d: snippets.keyword_subset(files(s, d), KEYWORDS).select("file_id"), f"with {FILES} select file_id from files where {_hit}")

#: Thousand millions of tokens of the annealing mixture.
PARTS = (("original", 83.94), ("algorithmic", 12.44), ("snippets", 2.71), ("textbooks", 0.91))


def three_parts(s, d, total: int = 1_000_000):
    """Original files, algorithmic ones (words of prose stand in for the keywords on prose) and synthetic ones, each to its share of `total` bytes."""
    f = files(s, d)
    prose = f.where(F.lower("text").contains("that it") | F.lower("text").contains("of the"))
    prompts = prose.select(F.col("file_id").alias("id"), F.lit("python").alias("lang"), F.col("text").alias("prompt"))
    made = snippets.keep_passing(snippets.generate(prompts).select("id", "lang", "code", "test"))
    synthetic = made.select(F.lit("snippets").alias("part"), F.col("id").alias("file_id"), F.octet_length(F.concat("code", "test")).cast("long").alias("n_bytes"))
    books = made.select(F.lit("textbooks").alias("part"), F.col("id").alias("file_id"), (F.octet_length(F.concat(F.lit("Explain step by step, as a textbook would: "), "code"))).cast("long").alias("n_bytes"))
    parts = f.select(F.lit("original").alias("part"), "file_id", "n_bytes").union(prose.select(F.lit("algorithmic"), "file_id", "n_bytes")).union(synthetic).union(books)
    sizes = parts.groupBy("part").agg(F.sum("n_bytes").alias("held"))
    budget = s.createDataFrame([(p, float(total * t / 100)) for p, t in PARTS], "part string, budget double")
    cut = F.least(F.lit(1.0), F.col("budget") / F.col("held")) * sampling.P31
    return parts.join(F.broadcast(sizes.join(budget, "part")), "part").where(sampling.unit_hash(F.concat_ws("/", "part", "file_id")) < cut).select("part", "file_id", "n_bytes")


add("anneal_three_parts", three_parts)

TESTED = [
    (1, "python", "def f(a):\n    return a + 1\n", "assert f(1) == 2\n"), (2, "python", "def f(a):\n    return a\n", "assert f(1) == 2\n"), (3, "python", "def f(a):\n    raise ValueError(a)\n", "f(1)\n"),
    (4, "python", "while True:\n    pass\n", "assert True\n"), (5, "python", "def f(:\n", "assert True\n"), (6, "python", "x = bytearray(1 << 34)\n", "assert x\n"), (7, "rust", "fn f() {}\n", "f();\n"), (8, "python", None, None),
]
VERDICTS = {1: "passed", 2: "failed", 3: "raised", 4: "timeout", 5: "invalid", 6: "memory", 7: "skipped", 8: "invalid"}
tested = lambda s: s.createDataFrame(TESTED, "id long, lang string, code string, test string")
add("synth_run_tests", lambda s, d: snippets.run_tests(tested(s), 2.0).select("id", "lang", "verdict"), "select id::bigint as id, lang, verdict from (values " + ", ".join(f"({i}, '{lang}', '{VERDICTS[i]}')" for i, lang, _, _ in TESTED) + ") v(id, lang, verdict)")
add("synth_keep_passing", lambda s, d: snippets.keep_passing(tested(s), seconds=2.0).select("id"), "select 1::bigint as id")


def seeds(s, d):
    """The best-labelled document of each source becomes a prompt, the generator answers, and what passes its test stays."""
    rows = table(s, d, "documents").join(table(s, d, "labels"), "doc_id")
    best = rows.groupBy("source").agg(F.max_by(F.struct("doc_id", "text"), F.struct("quality", "n_chars", -F.col("doc_id"))).alias("b"))
    prompts = best.select(F.col("b.doc_id").alias("id"), F.lit("python").alias("lang"), F.concat(F.lit("Write a function with a test about: "), F.col("b.text")).alias("prompt"))
    return snippets.keep_passing(snippets.generate(prompts)).select("id", F.length("prompt").alias("n_prompt"), "test")


add("synth_verified_seeds", seeds)
SENTENCES = r"""select page_id as id, trim(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<(script|style|nav)[^>]*>.*?</(script|style|nav)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '\s+', ' ', 'g')) as text from pages"""
add(
    "sft_page_sentences", lambda s, d: snippets.useful_sentences(table(s, d, "pages").select(F.col("page_id").alias("id"), recall.page_text(F.col("html")).alias("text"))).select("id", F.col("rank").cast("long").alias("rank"), "sentence"),
    rf"""with p as ({SENTENCES}), c as (select distinct id, trim(unnest(regexp_split_to_array(text, '[.!?]+\s+'))) as sentence from p), w as (select *, list_filter(regexp_split_to_array(lower(sentence), '\s+'), lambda x: x <> '') as w from c where sentence <> '')
select id, rank, sentence from (select id, sentence, row_number() over (partition by id order by len(list_distinct(w)) desc, sentence) as rank from w where len(w) between 6 and 60) where rank <= 5""",
)


def api_rows(s, d, modules=("json", "math", "string", "textwrap")):
    """Catalogue rows of modules by the table function; prompts are made from present signatures alone."""
    s.udtf.register("api_catalogue", ApiCatalogue)
    s.createDataFrame([(m,) for m in modules], "name string").createOrReplaceTempView("corpusmill_modules")
    return s.sql("select a.module, a.symbol, a.signature, concat('Show how to use ', a.module, '.', a.symbol, a.signature) as prompt from corpusmill_modules m, lateral api_catalogue(m.name) a")


add("sft_api_catalogue", api_rows)
add("vec_cosine_topk", lambda s, d: cosine(s, d), """with v as (select vec_id, list_transform(embedding, lambda x: x::double) as e from embeddings), n as (select vec_id, e, sqrt(list_dot_product(e, e)) as l from v)
select a.vec_id as query, b.vec_id as other, round(list_dot_product(a.e, b.e) / (a.l * b.l), 4) as sim from n a join n b on a.vec_id <> b.vec_id where a.vec_id % 20 = 0 qualify row_number() over (partition by a.vec_id order by round(list_dot_product(a.e, b.e) / (a.l * b.l), 4) desc, b.vec_id) <= 5""")


def cosine(s, d, k: int = 5):
    """The k nearest rows of each query (ids divisible by 20) among all rows: queries go out in blocks, every task keeps its k best, one exchange merges them."""
    import numpy as np
    import pandas as pd

    rows = table(s, d, "embeddings").select("vec_id", "embedding")
    queries = rows.where("vec_id % 20 = 0").orderBy("vec_id").collect()
    found = None
    for at in range(0, len(queries), 4096):
        ids = np.array([r[0] for r in queries[at : at + 4096]])
        unit = np.array([r[1] for r in queries[at : at + 4096]], np.float64)
        unit /= np.linalg.norm(unit, axis=1, keepdims=True)
        held = s.sparkContext.broadcast((ids, unit))

        def best(batches, held=held):
            ids, unit = held.value
            for batch in batches:
                if not len(batch):
                    continue
                other = np.array(batch["embedding"].to_list(), np.float64)
                sim = np.round(unit @ (other / np.linalg.norm(other, axis=1, keepdims=True)).T, 4)
                own = batch["vec_id"].to_numpy()
                sim[ids[:, None] == own[None, :]] = -2
                for q, row in zip(ids, sim):
                    top = np.lexsort((own, -row))[:k]
                    yield pd.DataFrame({"query": q, "other": own[top], "sim": row[top]})

        part = rows.mapInPandas(best, "query long, other long, sim double")
        found = part if found is None else found.union(part)
    from pyspark.sql import Window

    rank = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("sim"), "other"))
    return found.where("sim > -2").withColumn("r", rank).where(F.col("r") <= k).drop("r")



