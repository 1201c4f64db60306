"""Heuristic filter: rules are a metric, a comparison, a threshold, a weight and a goal; all that are chosen compile into one projection.

Lines, words and characters are staged once a row; no rule needs Python or a shuffle.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Rule:
    """Hit where low or high is passed; spark is an expression over text, L (lines), W (words), nL, nW, nC; duck the same for DuckDB."""

    name: str
    family: str
    goal: str
    spark: str
    duck: str
    low: float | None = None
    high: float | None = None
    weight: float = 1.0
    lang: str | None = None

    def hit(self, metric: Column) -> Column:
        tests = [metric < self.low] if self.low is not None else []
        tests += [metric > self.high] if self.high is not None else []
        return reduce(lambda a, b: a | b, tests) if tests else F.lit(False)

    def sql_hit(self, metric: str) -> str:
        tests = [f"{metric} < {self.low}::double"] if self.low is not None else []
        tests += [f"{metric} > {self.high}::double"] if self.high is not None else []
        return "(" + (" or ".join(tests) or "false") + ")"


def _share(part: str, whole: str) -> str:
    return f"coalesce(cast({part} as double) / nullif({whole}, 0), 0)"


def _count(pattern: str) -> tuple[str, str]:
    return f"regexp_count(text, '{pattern}')", f"len(regexp_extract_all(text, '{pattern}'))"


def _ratio(name: str, goal: str, pattern: str, whole: str, low: float | None, high: float | None, **more) -> Rule:
    a, b = _count(pattern)
    return Rule(name, more.pop("family", "text"), goal, _share(a, whole), _share(b, whole), low, high, **more)


def _lines(pattern: str, whole: str = "nL") -> tuple[str, str]:
    return _share(f"size(filter(L, x -> x rlike '{pattern}'))", whole), _share(f"len(list_filter(L, lambda x: regexp_matches(x, '{pattern}')))", whole)


def _most(n: int) -> tuple[str, str]:
    """Share of the characters that the n-gram which covers most of them covers, if it occurs twice or more."""
    s = f"if(nW < {n}, array(''), transform(sequence(1, greatest(nW - {n - 1}, 1)), i -> array_join(slice(W, i, {n}), ' ')))"
    run = "if(x <=> a.p, a.r + 1, 1)"
    best = f"aggregate(array_sort({s}), named_struct('p', cast(null as string), 'r', 0, 'b', 0), (a, x) -> named_struct('p', x, 'r', {run}, 'b', greatest(a.b, if({run} > 1, {run} * length(x), 0))), a -> a.b)"
    d = f"case when nW < {n} then [''] else list_transform(range(1, greatest(nW - {n - 2}, 2)), lambda i: array_to_string(W[i:i+{n - 1}], ' ')) end"
    most = f"list_max(list_transform(map_entries(list_histogram({d})), lambda e: case when e.value > 1 then e.value * length(e.key) else 0 end))"
    return _share(best, "nC"), _share(most, "nC")


def _entropy() -> tuple[str, str]:
    """Bits a character, from runs of the sorted characters."""
    runs = "aggregate(concat(array_sort(split(text, '')), array('')), named_struct('p', cast(null as string), 'r', 0L, 's', 0D), (a, x) -> named_struct('p', x, 'r', if(x <=> a.p, a.r + 1, 1L), 's', a.s + if(x <=> a.p or a.r = 0, 0D, a.r * log2(a.r))), a -> a.s)"
    return f"if(nC = 0, 4D, log2(greatest(nC, 1)) - {runs} / greatest(nC, 1))", "case when nC = 0 then 4.0::double else list_entropy(string_split(text, '')) end"


#: Share of n-grams that repeat an earlier one.
def _top(n: int) -> tuple[str, str]:
    s = f"if(nW < {n}, array(''), transform(sequence(1, greatest(nW - {n - 1}, 1)), i -> array_join(slice(W, i, {n}), ' ')))"
    d = f"case when nW < {n} then [''] else list_transform(range(1, greatest(nW - {n - 2}, 2)), lambda i: array_to_string(W[i:i+{n - 1}], ' ')) end"
    spark = f"get(transform(array({s}), g -> {_share('size(g) - size(array_distinct(g))', 'size(g)')}), 0)"
    duck = f"list_transform([{d}], lambda g: {_share('len(g) - len(list_distinct(g))', 'len(g)')})[1]"
    return spark, duck


STOPS = "'the','of','and','to','in','de','la','le','et','les','der','die','und','das','el','los','que','en','un','a'"
TEXT_RULES: list[Rule] = [
    Rule("bytes", "text", "size", "cast(octet_length(text) as double)", "octet_length(encode(text))::double", None, 1_000_000),
    Rule("chars_min", "text", "size", "cast(nC as double)", "nC::double", 20, None),
    Rule("lines", "text", "size", "cast(nL as double)", "nL::double", 1, 100_000),
    Rule("mean_line", "text", "format", _share("nC", "nL"), _share("nC", "nL"), None, 1_000),
    Rule("max_line", "text", "format", "cast(array_max(transform(L, x -> length(x))) as double)", "list_max(list_transform(L, lambda x: length(x)))::double", None, 100_000),
    Rule("words", "text", "size", "cast(nW as double)", "nW::double", 3, None),
    Rule("mean_word", "text", "format", _share("length(array_join(W, ''))", "nW"), _share("length(array_to_string(W, ''))", "nW"), 2, 20),
    _ratio("alpha_share", "format", r"\\p{L}", "nC", 0.4, None),
    _ratio("digit_share", "data", "[0-9]", "nC", None, 0.4),
    _ratio("symbol_word", "junk", "[%#*&$]", "nW", None, 0.1),
    Rule("dup_line", "text", "repetition", _share("nL - size(array_distinct(L))", "nL"), _share("nL - len(list_distinct(L))", "nL"), None, 0.3),
    Rule("dup_line_chars", "text", "repetition", _share("length(array_join(L, '')) - length(array_join(array_distinct(L), ''))", "nC"), _share("list_sum(list_transform(L, lambda x: length(x))) - list_sum(list_transform(list_distinct(L), lambda x: length(x)))", "nC"), None, 0.2),
    Rule("unique_word", "text", "repetition", f"if(nW < 20, 1D, {_share('size(array_distinct(W))', 'nW')})", f"case when nW < 20 then 1.0::double else {_share('len(list_distinct(W))', 'nW')} end", 0.3, None),
    *(Rule(f"dup_ngram_{n}", "text", "repetition", *_top(n), None, 0.3) for n in range(2, 11)),
    *(Rule(f"top_ngram_{n}", "text", "repetition", *_most(n), None, most) for n, most in ((2, 0.2), (3, 0.18), (4, 0.16))),
    Rule("entropy", "text", "repetition", *_entropy(), 2, 7),
    Rule("hex_share", "text", "data", _share("length(array_join(filter(W, x -> x rlike '^(0x)?[0-9a-fA-F]{8,}[,;]?$'), ''))", "nC"), _share("length(array_to_string(list_filter(W, lambda x: regexp_matches(x, '^(0x)?[0-9a-fA-F]{8,}[,;]?$')), ''))", "nC"), None, 0.4),
    Rule("blank_lines", "text", "format", *_lines("^[ ]*$"), None, 0.5),
    Rule("upper_share", "text", "shouting", _share(r"regexp_count(text, '\\p{Lu}')", r"regexp_count(text, '\\p{L}')"), _share(r"len(regexp_extract_all(text, '\p{Lu}'))", r"len(regexp_extract_all(text, '\p{L}'))"), None, 0.3),
    _ratio("pipe_word", "data", "[|]", "nW", None, 0.1),
    Rule("ellipsis_lines", "text", "format", *_lines("([.][.][.]|…)$"), None, 0.3),
    Rule("bullet_lines", "text", "format", *_lines("^[ ]*[-*•]"), None, 0.9),
    Rule("stop_words", "text", "language", f"if(nW < 50, 1D, cast(size(array_intersect(transform(W, x -> lower(x)), array({STOPS}))) as double))", f"case when nW < 50 then 1.0::double else len(list_intersect(list_transform(W, lambda x: lower(x)), [{STOPS}]))::double end", 1, None),
    _ratio("control_chars", "binary", "[\\x00-\\x08\\x0e-\\x1f]", "nC", None, 0.01),
    Rule("long_token", "text", "data", "cast(coalesce(array_max(transform(W, x -> length(x))), 0) as double)", "coalesce(list_max(list_transform(W, lambda x: length(x))), 0)::double", None, 1_000),
    Rule("generated_mark", "text", "authored", "cast(lower(array_join(slice(L, 1, 5), ' ')) rlike 'generated by|do not edit|auto-generated' as double)", "regexp_matches(lower(array_to_string(L[1:5], ' ')), 'generated by|do not edit|auto-generated')::int::double", None, 0.5),
    Rule("placeholder", "text", "filler", "cast(lower(text) rlike 'lorem ipsum|insert text here' as double)", "regexp_matches(lower(text), 'lorem ipsum|insert text here')::int::double", None, 0.5),
    _ratio("exclaim_word", "shouting", "!", "nW", None, 0.1),
]
for _k, _r in enumerate(TEXT_RULES):  # character classes are written once, as Spark's parser wants them
    if _r.name in ("alpha_share", "control_chars"):
        TEXT_RULES[_k] = Rule(_r.name, "text", _r.goal, _r.spark.replace("[\\x00-\\x08\\x0e-\\x1f]", r"[\\x00-\\x08\\x0e-\\x1f]"), _r.duck.replace(r"\\p", r"\p"), _r.low, _r.high)

_CODE_LINES = r"^[ \t]*[^ \t]"
_COMMENT = "^[ ]*(//|#|/[*]|[*]|<!--)"


def _code(name: str, goal: str, pattern: str, high: float | None, lang: str | None = None, low: float | None = None) -> Rule:
    a, b = _lines(pattern, "nB")
    return Rule(name, "code" if lang is None else "language", goal, a, b, low, high, lang=lang)


def _whole(name: str, goal: str, pattern: str, whole: str, high: float | None, lang: str | None = None, low: float | None = None) -> Rule:
    a, b = _count(pattern)
    return Rule(name, "code" if lang is None else "language", goal, _share(a, whole), _share(b, whole), low, high, lang=lang)


_DEF = "^[ ]*(def |func |function |(public |private |static |final )*[A-Za-z_]+[ ][A-Za-z_]+[(].*[)][ ]*[{])"
CODE_RULES: list[Rule] = [
    _code("variables", "logic", "^[ ]*[A-Za-z_][A-Za-z_0-9 ]*=[^=]", 0.9),
    _code("functions", "logic", _DEF, 0.6),
    Rule("mean_fn_len", "code", "format", _share("nB", f"size(filter(L, x -> x rlike '{_DEF}'))"), _share("nB", f"len(list_filter(L, lambda x: regexp_matches(x, '{_DEF}')))"), None, 200),
    _code("comment_share", "logic", _COMMENT, 0.8),
    _code("import_share", "self-contained", "^[ ]*(import |from |#include|using |require)", 0.5),
    _code("assert_share", "logic", "^[ ]*(assert|self[.]assert|expect[(])", 0.4),
    _code("print_share", "logic", "(print|println|printf|console[.]log|fmt[.]Print)", 0.4),
    _whole("string_share", "data", '"[^"]*"', "nB", 8.0),
    _whole("number_share", "data", "(^|[^A-Za-z0-9_])[0-9]+", "nW", 0.5),
    Rule("bracket_balance", "code", "format", _share("abs(regexp_count(text, '[(\\\\[{]') - regexp_count(text, '[)\\\\]}]'))", "regexp_count(text, '[(\\\\[{)\\\\]}]')"), _share("abs(len(regexp_extract_all(text, '[(\\[{]')) - len(regexp_extract_all(text, '[)\\]}]')))", "len(regexp_extract_all(text, '[(\\[{)\\]}]'))"), None, 0.2),
    Rule("max_indent", "code", "format", "cast(array_max(transform(L, x -> length(regexp_extract(x, '^[ ]*', 0)))) as double)", "list_max(list_transform(L, lambda x: length(regexp_extract(x, '^[ ]*', 0))))::double", None, 100),
    _code("todo_share", "logic", "(TODO|FIXME)", 0.3),
    Rule("code_lines", "code", "size", f"cast(size(filter(L, x -> x rlike '[^ ]' and not x rlike '{_COMMENT}')) as double)", f"len(list_filter(L, lambda x: regexp_matches(x, '[^ ]') and not regexp_matches(x, '{_COMMENT}')))::double", 3, None),
    _code("control_kw", "logic", "(^|[^A-Za-z_])(if|for|while|switch|return)([^A-Za-z_]|$)", None, low=0.005),
    Rule("mixed_indent", "code", "format", _share("least(size(filter(L, x -> x like '\\t%')), size(filter(L, x -> x like ' %')))", "nL"), _share("least(len(list_filter(L, lambda x: x like chr(9) || '%')), len(list_filter(L, lambda x: x like ' %')))", "nL"), None, 0.4),
    _code("stub_share", "logic", "^[ ]*(pass|[.][.][.]|[{][ ]*[}])[ ]*$", 0.8),
    _code("path_depends", "self-contained", "^[ ]*(from [.]|#include \"|require[(].[.])", 0.6),
    _code("config_like", "logic", "^[A-Za-z_.]+[ ]*=[ ]*[^ ]+$", 0.8),
]
LANGUAGE_RULES: list[Rule] = [
    _code("pass_share", "logic", "^[ ]*pass[ ]*$", 0.3, "python"), _code("import_lines", "self-contained", "^(import |from )", 0.5, "python"), _code("main_only", "logic", "__main__", 0.5, "python"),
    _code("goto_share", "logic", "goto ", 0.1, "c"), _code("preprocessor", "logic", "^[ ]*#", 0.5, "c"), _code("macro_table", "data", "^#define", 0.5, "c"),
    _code("preprocessor", "logic", "^[ ]*#", 0.5, "cpp"), _code("template_only", "logic", "^template", 0.5, "cpp"), _code("access_labels", "logic", "^[ ]*(public|private|protected):", 0.3, "cpp"),
    _code("using_share", "self-contained", "^using ", 0.5, "csharp"), _code("attribute_share", "logic", "^[ ]*[\\[][A-Z]", 0.5, "csharp"), _code("empty_property", "logic", "get; set;", 0.8, "csharp"),
    _code("import_lines", "self-contained", "^import ", 0.5, "java"), _code("getter_setter", "logic", "(get|set)[A-Z][A-Za-z]*[(]", 0.8, "java"), _code("annotation_only", "logic", "^[ ]*@", 0.5, "java"),
    _whole("semicolons", "format", ";", "nL", 10, "javascript"), _code("console_share", "logic", "console[.]", 0.4, "javascript"), _code("require_share", "self-contained", "(require[(]|^import )", 0.5, "javascript"),
    _code("error_checks", "logic", "err != nil", 0.4, "go"), _code("generated", "authored", "Code generated", 0.0, "go"), _code("struct_only", "logic", "^type .* struct", 0.5, "go"),
    _whole("tag_per_char", "format", "<[^>]*>", "nC", 0.2, "html"), _code("script_style", "logic", "<(script|style)", 0.7, "html"), _code("data_uri", "data", "data:[a-z]+/[a-z]+;base64", 0.3, "html"),
]
for _k, _r in enumerate(LANGUAGE_RULES):
    if _r.name == "attribute_share":
        LANGUAGE_RULES[_k] = Rule(_r.name, _r.family, _r.goal, _r.spark.replace("[\\[]", "[\\\\[]"), _r.duck, None, _r.high, lang=_r.lang)
#: Further rules a language, as name, goal, pattern of a line and the highest share of lines with it.
MORE: dict[str, list[tuple[str, str, str, float]]] = {
    "python": [
        ("wildcard_import", "self-contained", "^from .* import [*]", 0.2), ("global_share", "logic", "^[ ]*global ", 0.2), ("eval_share", "logic", "(eval|exec)[(]", 0.2), ("nested_lambda", "format", "lambda .*lambda", 0.2), ("print_only", "logic", "^[ ]*print[(]", 0.6),
        ("decorator_share", "logic", "^[ ]*@", 0.4), ("docstring_marks", "format", '"""', 0.5), ("dunder_assign", "data", "^__[a-z]+__", 0.4), ("relative_import", "self-contained", "^from [.]", 0.4),
    ],
    "c": [
        ("include_share", "self-contained", "^#include", 0.4), ("typedef_only", "logic", "^typedef", 0.5), ("extern_share", "self-contained", "^extern ", 0.5), ("assembly_share", "logic", "(__asm__|asm[ ]*[(])", 0.3), ("hex_table", "data", "0x[0-9A-Fa-f]+,.*0x[0-9A-Fa-f]+,", 0.5),
        ("pragma_share", "logic", "^#pragma", 0.3), ("declaration_only", "logic", "^[A-Za-z_][A-Za-z_0-9 *]*[(][^{]*[)];$", 0.7), ("brace_lines", "format", "^[ ]*[{}][ ]*$", 0.6), ("printf_share", "logic", "printf[(]", 0.6),
    ],
    "cpp": [
        ("include_share", "self-contained", "^#include", 0.4), ("using_namespace", "self-contained", "^using namespace", 0.3), ("forward_only", "logic", "^(class|struct) [A-Za-z_]+;$", 0.5), ("operator_share", "logic", "operator[ ]*[^a-z ]", 0.5), ("cast_share", "logic", "(static|dynamic|reinterpret|const)_cast", 0.5),
        ("stream_output", "logic", "(cout|cerr)[ ]*<<", 0.6), ("macro_share", "data", "^#define", 0.5), ("friend_share", "logic", "^[ ]*friend ", 0.3), ("empty_body", "logic", "[)][ ]*[{][ ]*[}]", 0.5),
    ],
    "csharp": [
        ("region_share", "format", "^[ ]*#(region|endregion)", 0.3), ("auto_property", "logic", "[{] get; (private |protected )?set; [}]", 0.7), ("console_share", "logic", "Console[.]Write", 0.4), ("partial_share", "self-contained", "partial class", 0.3), ("not_implemented", "logic", "NotImplementedException", 0.3),
        ("designer_code", "authored", "(InitializeComponent|[.]Designer)", 0.1), ("doc_comment", "logic", "^[ ]*///", 0.7), ("constant_table", "data", "^[ ]*(public |private )?const ", 0.6), ("namespace_only", "logic", "^namespace", 0.5),
    ],
    "java": [
        ("print_share", "logic", "System[.]out[.]print", 0.4), ("override_share", "logic", "@Override", 0.4), ("empty_catch", "logic", "catch[ ]*[(][^)]*[)][ ]*[{][ ]*[}]", 0.2), ("interface_only", "logic", "^[ ]*(public )?interface", 0.4), ("serial_share", "authored", "serialVersionUID", 0.2),
        ("package_only", "logic", "^package ", 0.5), ("constant_table", "data", "static final", 0.6), ("template_mark", "authored", "Auto-generated", 0.1), ("field_copy", "logic", "this[.][a-zA-Z]+ = [a-zA-Z]+;", 0.6),
    ],
    "javascript": [
        ("packed_line", "format", "[;,][^ ].*[;,][^ ].*[;,][^ ]", 0.7), ("var_share", "logic", "^[ ]*var ", 0.7), ("eval_share", "logic", "(eval|Function)[(]", 0.2), ("selector_share", "logic", "[$][(]", 0.7), ("strict_only", "logic", "use strict", 0.3),
        ("export_share", "self-contained", "^export ", 0.7), ("prototype_share", "logic", "[.]prototype[.]", 0.6), ("alert_share", "logic", "alert[(]", 0.3), ("number_table", "data", "^[ ]*[0-9.,]+[ ]*$", 0.5),
    ],
    "go": [
        ("import_share", "self-contained", '^[ ]*(import|")', 0.5), ("panic_share", "logic", "panic[(]", 0.3), ("print_share", "logic", "fmt[.]Print", 0.5), ("blank_assign", "logic", "^[ ]*_ = ", 0.3), ("constant_table", "data", "(^const|iota)", 0.5),
        ("tag_share", "data", "json:", 0.6), ("routine_share", "logic", "go func", 0.4), ("defer_share", "logic", "defer ", 0.4), ("nolint_share", "format", "nolint", 0.3),
    ],
    "html": [
        ("inline_style", "format", "style=", 0.6), ("table_share", "format", "<t[dr]", 0.7), ("hidden_share", "format", "display: *none", 0.4), ("comment_share", "logic", "<!--", 0.4), ("iframe_share", "self-contained", "<iframe", 0.3),
        ("meta_share", "format", "<meta", 0.5), ("image_only", "logic", "<img", 0.6), ("link_list", "logic", "<a ", 0.7),
    ],
}
LANGUAGE_RULES += [_code(name, goal, pattern, high, lang) for lang, rows in MORE.items() for name, goal, pattern, high in rows]
_SEEN = "<(script|style)[^>]*>[^<]*</(script|style)>"
LANGUAGE_RULES.append(Rule("visible_text", "language", "logic", _share(f"length(trim(regexp_replace(regexp_replace(text, '{_SEEN}', ''), '<[^>]*>', '')))", "nC"), _share(f"length(trim(regexp_replace(regexp_replace(text, '{_SEEN}', '', 'g'), '<[^>]*>', '', 'g')))", "nC"), 0.2, None, lang="html"))
BASELINE = ("mean_line", "max_line", "alpha_share", "generated_mark", "chars_min")
REGISTRY = TEXT_RULES + CODE_RULES + LANGUAGE_RULES


def _once(df: DataFrame, columns: dict[str, Column]) -> DataFrame:
    """df with columns that are computed once a row: no filter or projection above copies what an inlined row holds into itself."""
    return df.select("*", F.inline(F.array(F.struct(*(c.alias(n) for n, c in columns.items())))))


def staged(df: DataFrame) -> DataFrame:
    """Lines, words and sizes, once a row."""
    out = _once(df, {"L": F.split("text", "\n"), "W": F.filter(F.split("text", r"\s+"), lambda x: x != ""), "nC": F.length("text")})
    return _once(out, {"nL": F.size("L"), "nW": F.size("W"), "nB": F.size(F.filter("L", lambda x: x.rlike("[^ ]")))})


STAGED = r"select *, len(L) as nL, len(W) as nW, len(list_filter(L, lambda x: regexp_matches(x, '[^ ]'))) as nB from (select *, string_split(text, chr(10)) as L, list_filter(regexp_split_to_array(text, '\s+'), lambda x: x <> '') as W, length(text) as nC from {source})"


def metrics(df: DataFrame, rules: list[Rule]) -> DataFrame:
    return _once(staged(df), {f"m_{r.name}": F.expr(r.spark) for r in rules})


def apply_rules(df: DataFrame, rules: list[Rule], policy: str = "any", cutoff: float = 1.0) -> DataFrame:
    """df's columns with the metrics, violations, penalty and keep."""
    out = metrics(df, rules)
    marks = F.array_compact(F.array(*(F.when(r.hit(F.col(f"m_{r.name}")), F.lit(r.name)) for r in rules)))
    weigh = reduce(lambda a, b: a + b, (F.when(r.hit(F.col(f"m_{r.name}")), F.lit(r.weight)).otherwise(0.0) for r in rules))
    out = out.withColumns({"violations": marks, "penalty": weigh}).drop("L", "W", "nL", "nW", "nC", "nB")
    return out.withColumn("keep", F.size("violations") == 0 if policy == "any" else F.col("penalty") < cutoff)


def scored_sql(rules: list[Rule], source: str) -> str:
    hits = ", ".join(f"case when {r.sql_hit(r.duck)} then '{r.name}' end" for r in rules)
    weigh = " + ".join(f"case when {r.sql_hit(r.duck)} then {r.weight}::double else 0 end" for r in rules)
    return f"select *, list_filter([{hits}], lambda x: x is not null) as violations, {weigh} as penalty from ({STAGED.format(source=source)})"


def catalogue(spark: SparkSession) -> DataFrame:
    number = lambda x: None if x is None else float(x)
    rows = [(r.name, r.family, r.goal, r.lang or "", number(r.low), number(r.high), r.weight) for r in REGISTRY]
    return spark.createDataFrame(rows, "name string, family string, goal string, lang string, low double, high double, weight double")


def report(scored: DataFrame) -> DataFrame:
    """(rule, lang, n_hit, n_alone): files that a rule removes, and those that it removes alone."""
    return scored.select("lang", F.size("violations").alias("k"), F.explode("violations").alias("rule")).groupBy("rule", "lang").agg(F.count(F.lit(1)).alias("n_hit"), F.sum((F.col("k") == 1).cast("long")).alias("n_alone"))


def sweep(df: DataFrame, rule: Rule, grid: list[float]) -> DataFrame:
    """For each threshold of a rule's upper side (of its lower one, if it has no upper) in one pass: removed rows and share, and the Jensen-Shannon divergence of kept from all languages."""
    out = F.col("m") > F.col("threshold") if rule.high is not None else F.col("m") < F.col("threshold")
    m = metrics(df, [rule]).select("lang", F.col(f"m_{rule.name}").alias("m"))
    rows = m.select("lang", "m", F.explode(F.array(*map(F.lit, grid))).alias("threshold"))
    cells = rows.groupBy("threshold", "lang").agg(F.count(F.lit(1)).alias("n"), F.sum(out.cast("long")).alias("out"))
    tot = cells.groupBy("threshold").agg(F.sum("n").alias("n_all"), F.sum("out").alias("out_all"))
    p, q = F.col("n") / F.col("n_all"), (F.col("n") - F.col("out")) / F.greatest(F.col("n_all") - F.col("out_all"), F.lit(1))
    mid = (p + q) / 2
    part = F.when(p > 0, p * F.log(2.0, p / mid)).otherwise(0.0) + F.when(q > 0, q * F.log(2.0, q / mid)).otherwise(0.0)
    return cells.join(F.broadcast(tot), "threshold").groupBy("threshold").agg(F.max("out_all").alias("removed"), F.round(F.max(F.col("out_all") / F.col("n_all")), 6).alias("share"), F.round(F.sum(part) / 2, 6).alias("divergence"))


def accuracy(scored: DataFrame, labels: DataFrame) -> DataFrame:
    """Precision and recall of rejection against low quality labels."""
    both = scored.join(labels, scored["file_id"] == labels["doc_id"]).select((~F.col("keep")).cast("int").alias("out"), (1 - F.col("quality")).alias("low"))
    hit = F.sum(F.col("out") * F.col("low"))
    return both.agg(F.count(F.lit(1)).alias("n"), hit.cast("long").alias("hits"), F.round(hit / F.sum("out"), 6).alias("precision"), F.round(hit / F.sum("low"), 6).alias("recall"))


def boundary(df: DataFrame, rule: Rule, m: int) -> DataFrame:
    """The m files nearest to a rule's threshold."""
    limit = rule.high if rule.high is not None else rule.low
    near = metrics(df, [rule]).select("file_id", F.round(F.abs(F.col(f"m_{rule.name}") - limit), 6).alias("distance"))
    return near.orderBy("distance", "file_id").limit(m)
