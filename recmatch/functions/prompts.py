"""Questions as text, and answers as labels."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

ASK_PAIR = "Say Yes if both entries describe one real thing, else No."
ASK_TRIPLE = "Which entry fits the given one better, A or B?"
ASK_LIST = "Give the number of the entry that describes the same thing."
NONE = "0: none of these"
#: Words of a question without its entries: the instruction and a mark before each entry. A list has a mark an option more.
PAIR_WORDS, TRIPLE_WORDS, LIST_WORDS, NONE_WORDS, EXAMPLE_WORDS = len(ASK_PAIR.split()) + 2, len(ASK_TRIPLE.split()) + 3, len(ASK_LIST.split()) + 1, len(NONE.split()), 4


def record_text(names: list[str], prefix: str) -> Column:
    """name: value lines; attributes without a value are left out."""
    return F.concat_ws("; ", *(F.when(F.col(f"{prefix}{n}").isNotNull(), F.concat(F.lit(f"{n}: "), F.col(f"{prefix}{n}").cast("string"))) for n in names))


def render_pair(a: Column, b: Column, rules: str | None = None, examples: Column | None = None) -> Column:
    parts = [F.lit(ASK_PAIR), *([F.lit(rules)] if rules else []), *([examples] if examples is not None else [])]
    return F.concat_ws("\n", *parts, F.concat(F.lit("First: "), a), F.concat(F.lit("Second: "), b))


def render_example(a: Column, b: Column, label: Column) -> Column:
    return F.concat_ws("\n", F.concat(F.lit("First: "), a), F.concat(F.lit("Second: "), b), F.concat(F.lit("Answer: "), F.when(label == 1, "Yes").otherwise("No")))


def render_triple(anchor: Column, a: Column, b: Column) -> Column:
    return F.concat_ws("\n", F.lit(ASK_TRIPLE), F.concat(F.lit("Given: "), anchor), F.concat(F.lit("A: "), a), F.concat(F.lit("B: "), b))


def render_list(anchor: Column, options: Column, opt_out: bool) -> Column:
    """options: array of texts in order."""
    last = F.lit(NONE) if opt_out else None
    numbered = F.array_join(F.transform(options, lambda o, i: F.concat((i + 1).cast("string"), F.lit(": "), o)), "\n")
    return F.concat_ws("\n", F.lit(ASK_LIST), F.concat(F.lit("Given: "), anchor), numbered, *([last] if last is not None else []))


def parse_yes_no(answer: Column) -> Column:
    """True or false if exactly one of the words is there, else null."""
    low = F.lower(answer)
    yes, no = low.rlike(r"(^|[^a-z])yes([^a-z]|$)"), low.rlike(r"(^|[^a-z])no([^a-z]|$)")
    return F.when(yes & ~no, True).when(no & ~yes, False)


def parse_ab(answer: Column) -> Column:
    a, b = answer.rlike(r"(^|[^A-Za-z])A([^A-Za-z]|$)"), answer.rlike(r"(^|[^A-Za-z])B([^A-Za-z]|$)")
    return F.when(a & ~b, "A").when(b & ~a, "B")


def parse_choice(answer: Column, n: Column) -> Column:
    """The first number, if it is from 0 to n."""
    v = F.regexp_extract(answer, r"([0-9]+)", 1).try_cast("int")
    return F.when(v <= n, v)


def count_tokens(text: Column, scheme: str = "word") -> Column:
    """Words, or characters over four rounded up."""
    if scheme == "chars4":
        return F.ceil(F.length(text) / 4).cast("long")
    return F.size(F.filter(F.split(text, r"\s+"), lambda w: w != "")).cast("long")
