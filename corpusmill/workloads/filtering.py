"""Rule workloads."""

from __future__ import annotations

from pyspark.sql import functions as F

from corpusmill.operators import rules
from corpusmill.operators.rules import CODE_RULES, LANGUAGE_RULES, TEXT_RULES
from corpusmill.schema import FILES, files, table
from corpusmill.workloads.catalog import add
from corpusmill.workloads.fixtures import CODE_VALUES, code_files

BY = {r.name: r for r in TEXT_RULES}
BEST = [BY[n] for n in ("symbol_word", "dup_line", "unique_word", "dup_ngram_2", "upper_share", "pipe_word", "exclaim_word")]


def one(source: str, r: rules.Rule, key: str) -> str:
    return f"with {source} select {key}, round(m, 6) as metric, {r.sql_hit('m')} as hit from (select {key}, {r.duck} as m from ({rules.STAGED.format(source='files')}))"


def view(df, r, key):
    m = rules.metrics(df, [r]).select(key, F.col(f"m_{r.name}").alias("m"))
    return m.select(key, F.round("m", 6).alias("metric"), r.hit(F.col("m")).alias("hit"))


for _r in TEXT_RULES:
    add(f"rule_nl_{_r.name}", lambda s, d, r=_r: view(files(s, d), r, "file_id"), one(FILES, _r, "file_id"))
#: Code rules that run over the documents as files; the others have hand-written files.
ON_DOCUMENTS = ("assert_share", "bracket_balance", "code_lines", "comment_share", "config_like")
for _r in CODE_RULES:
    if _r.name in ON_DOCUMENTS:
        add(f"rule_code_{_r.name}", lambda s, d, r=_r: view(files(s, d), r, "file_id"), one(FILES, _r, "file_id"))
    else:
        add(f"rule_code_{_r.name}", lambda s, d, r=_r: view(code_files(s), r, "file_id"), one(CODE_VALUES, _r, "file_id"))
for _r in LANGUAGE_RULES:
    src = CODE_VALUES.replace("as files_all)", f"as files_all where lang = '{_r.lang}')")
    add(f"rule_lang_{_r.lang}_{_r.name}", lambda s, d, r=_r: view(code_files(s).where(F.col("lang") == r.lang), r, "file_id"), one(src, _r, "file_id"))


def nums(x: float | None) -> str:
    return "null::double" if x is None else f"{float(x)}::double"


add("rules_catalogue", lambda s, d: rules.catalogue(s), "select * from (values " + ", ".join(f"('{r.name}', '{r.family}', '{r.goal}', '{r.lang or ''}', {nums(r.low)}, {nums(r.high)}, {nums(r.weight)})" for r in rules.REGISTRY) + ") t(name, family, goal, lang, low, high, weight)")
SCORED = f"with {FILES}, s as ({rules.scored_sql(BEST, 'files')})"
add("rules_violations", lambda s, d: rules.apply_rules(files(s, d), BEST).select("file_id", F.array_join("violations", ",").alias("violations"), F.round("penalty", 6).alias("penalty")), f"{SCORED} select file_id, array_to_string(violations, ',') as violations, round(penalty, 6) as penalty from s")
add("rules_keep_any", lambda s, d: rules.apply_rules(files(s, d), BEST).where("keep").select("file_id"), f"{SCORED} select file_id from s where len(violations) = 0")
add("rules_keep_weighted", lambda s, d: rules.apply_rules(files(s, d), BEST, "weighted", 2.0).where("keep").select("file_id"), f"{SCORED} select file_id from s where penalty < 2")
add("rules_report", lambda s, d: rules.report(rules.apply_rules(files(s, d), BEST)), f"{SCORED} select rule, lang, count(*)::bigint as n_hit, sum((k = 1)::int)::bigint as n_alone from (select lang, len(violations) as k, unnest(violations) as rule from s) group by rule, lang")
SYM = BY["symbol_word"]
GRID = [0.05, 0.1, 0.2, 0.5, 1.0]


def sweep_sql(rule: rules.Rule, grid: list[float]) -> str:
    side = ">" if rule.high is not None else "<"
    return f"""with {FILES}, m as (select lang, {rule.duck} as m from ({rules.STAGED.format(source='files')})), c as (select t as threshold, lang, count(*) as n, sum((m {side} t)::int) as o from m, (values {', '.join(f'({g}::double)' for g in grid)}) g(t) group by 1, 2),
z as (select *, sum(n) over (partition by threshold) as nn, sum(o) over (partition by threshold) as oo from c), pq as (select threshold, nn, oo, n::double / nn as p, (n - o)::double / greatest(nn - oo, 1) as q from z)
select threshold, max(oo)::bigint as removed, round(max(oo::double / nn), 6) as share, round(sum(case when p > 0 then p * log2(p / ((p + q) / 2)) else 0 end + case when q > 0 then q * log2(q / ((p + q) / 2)) else 0 end) / 2, 6) as divergence from pq group by threshold"""


SWEEP = sweep_sql(SYM, GRID)
LOW_GRID = [0.2, 0.3, 0.4, 0.5]
add("rules_threshold_sweep_low", lambda s, d: rules.sweep(files(s, d), BY["unique_word"], LOW_GRID), sweep_sql(BY["unique_word"], LOW_GRID))
add("rules_threshold_sweep", lambda s, d: rules.sweep(files(s, d), SYM, GRID), SWEEP)
add("rules_distribution_shift", lambda s, d: rules.sweep(files(s, d), SYM, [0.1]).select("divergence"), SWEEP.replace(", ".join(f"({g}::double)" for g in GRID), "(0.1::double)").replace("select threshold, max(oo)::bigint as removed, round(max(oo::double / nn), 6) as share,", "select"))
add("rules_vs_labels", lambda s, d: rules.accuracy(rules.apply_rules(files(s, d), BEST), table(s, d, "labels")), f"{SCORED}, j as (select (len(violations) > 0)::int as o, 1 - quality as low from s join labels on file_id = doc_id) select count(*)::bigint as n, sum(o * low)::bigint as hits, round(sum(o * low)::double / sum(o), 6) as precision, round(sum(o * low)::double / sum(low), 6) as recall from j")
add("rules_boundary_topk", lambda s, d: rules.boundary(files(s, d), SYM, 20), f"with {FILES} select file_id, round(abs({SYM.duck} - 0.1::double), 6) as distance from ({rules.STAGED.format(source='files')}) order by distance, file_id limit 20")
base = [BY[n] for n in rules.BASELINE]
add(
    "rules_baseline_vs_full", lambda s, d: rules.apply_rules(files(s, d), base).agg(F.lit("baseline").alias("ruleset"), F.sum(F.col("keep").cast("long")).alias("kept")).unionByName(rules.apply_rules(files(s, d), TEXT_RULES).agg(F.lit("full").alias("ruleset"), F.sum(F.col("keep").cast("long")).alias("kept"))),
    f"with {FILES}, b as ({rules.scored_sql(base, 'files')}), f as ({rules.scored_sql(TEXT_RULES, 'files')}) select 'baseline' as ruleset, sum((len(violations) = 0)::int)::bigint as kept from b union all select 'full', sum((len(violations) = 0)::int)::bigint from f",
)
