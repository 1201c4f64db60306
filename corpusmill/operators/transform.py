"""Notice removal and masking of personal data, as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: What marks a notice, license lines of prose, and patterns of personal data (order of masking).
NOTICE = "[Cc]opyright"
COMMENT_LINE = r"^\s*(#|//)"
LICENSE_LINE = r"\n[^\n]*([Ll]icensed under|MIT License|General Public License)[^\n]*"
KINDS = {
    "secret": r"(token|password|secret|api_key)\s*[:=]\s*\"[^\"\n]{6,}\"",
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}",
    "phone": r"\+[0-9]{1,3} \([0-9]{3}\) [0-9]{3}-[0-9]{4}",
    "card": r"[0-9]{16}",
}
#: The same matches in time that is linear in a run of name characters: a match begins where a run does, or where the last match ended.
LINEAR = KINDS | {"email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"}
#: What must be in a text for a pattern to match it, so that most rows skip the pattern.
CUES = {"secret": "\"", "email": "@", "ip": ".", "phone": "+", "card": ""}
#: People named beside a mail address, after an author's tag or in a signature.
NAMED = r"((?:@author|Author:|author:|Written by|Signed-off-by:)[ \t]+)[A-Z][a-z]+(?:[ \t]+[A-Z][a-z.]*){0,3}"
NAME_MAIL = r"[A-Z][a-z]+(?: [A-Z][a-z.]*){0,3}( ?<[^<>\s]+@[^<>\s]+>)"
OCTET = r"(25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
IP_VALID = rf"{OCTET}\.{OCTET}\.{OCTET}\.{OCTET}"


def strip_notice(text: Column, where: str = "head") -> Column:
    """Without the leading comment that holds a notice, however long it is: a block comment, or the run of line comments at the head.

    Lines and places are found by array functions, so long comments need no recursion of a pattern. Null stays null.
    """
    if where != "head":
        return F.regexp_replace(text, LICENSE_LINE, "")
    flags = F.transform(F.split(text, "\n"), lambda x: F.when(x.rlike(COMMENT_LINE), 1).when(F.trim(x) == "", 0).otherwise(2))
    lead = F.get(F.transform(F.array(flags), lambda f: F.when(F.array_contains(f, 2), F.slice(f, 1, (F.array_position(f, 2) - 1).cast("int"))).otherwise(f)), 0)
    last = F.get(F.transform(F.array(lead), lambda f: F.when(F.array_contains(f, 1), F.size(f) - F.array_position(F.reverse(f), 1) + 1).otherwise(0)), 0).cast("int")
    cut = F.get(F.transform(F.array(F.struct(F.split(text, "\n").alias("l"), last.alias("n"))), lambda p: F.when(F.exists(F.slice(p["l"], 1, p["n"]), lambda x: x.rlike(NOTICE)), F.array_join(F.slice(p["l"], p["n"] + 1, F.greatest(F.size(p["l"]) - p["n"], F.lit(0))), "\n")).otherwise(text)), 0)
    head = F.ltrim(text)
    shut = F.instr(head, "*/")
    block = F.when((shut > 0) & F.substring(head, F.lit(1), shut).rlike(NOTICE), F.regexp_replace(F.substring(head, shut + 2, F.length(head)), r"^\s+", "")).otherwise(text)
    return F.when(~text.rlike(NOTICE), text).when(head.startswith("/*"), block).otherwise(cut)


def mask_names(text: Column, placeholder: str = "<name>") -> Column:
    """Names of people in the contexts that tell them: an author's tag or a signature, or a mail address beside the name."""
    return F.regexp_replace(F.regexp_replace(text, NAME_MAIL, placeholder + "$1"), NAMED, "$1" + placeholder)


def mask(text: Column, kinds: tuple[str, ...] = tuple(KINDS), placeholder: str = "<{}>") -> Column:
    for kind in kinds:
        masked = F.regexp_replace(text, LINEAR[kind], placeholder.format(kind))
        text = F.when(text.contains(CUES[kind]), masked).otherwise(text) if CUES[kind] else masked
    return text


def luhn(digits: Column) -> Column:
    """Whether a string of digits passes the check sum."""
    n = F.length(digits)
    each = F.transform(F.sequence(F.lit(1), n), lambda i: F.substring(digits, i, F.lit(1)).cast("int") * F.when((n - i) % 2 == 1, 2).otherwise(1))
    return F.aggregate(F.transform(each, lambda x: F.when(x > 9, x - 9).otherwise(x)), F.lit(0), lambda a, b: a + b) % 10 == 0
