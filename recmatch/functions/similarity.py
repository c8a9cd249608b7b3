"""Attribute similarities as SQL text, for Spark and for the oracles."""

from __future__ import annotations

from recmatch.plans.workloads import Attribute, Workload


def words(x: str, name: str) -> str:
    """Distinct lower-cased words: runs of letters and digits."""
    if name == "spark":
        return rf"array_distinct(filter(split(lower({x}), '[^\\pL\\pN]+'), t -> t <> ''))"
    return rf"list_distinct(list_filter(string_split_regex(lower({x}), '[^\pL\pN]+'), lambda t: t <> ''))"


def qgrams(x: str, name: str) -> str:
    """Distinct 3-character substrings of the lower-cased text."""
    s = f"lower({x})"
    if name == "spark":
        return f"array_distinct(transform(sequence(1, greatest(length({s}) - 2, 1)), i -> substr({s}, i, 3)))"
    return f"list_distinct(list_transform(range(1, greatest(length({s}) - 2, 1) + 1), lambda i: substr({s}, i, 3)))"


def _common(a: str, b: str, name: str) -> tuple[str, str]:
    if name == "spark":
        return f"size(array_intersect({a}, {b}))", f"size(array_union({a}, {b}))"
    return f"len(list_intersect({a}, {b}))", f"len(list_distinct(list_concat({a}, {b})))"


def similarity(t: Attribute, a: str, b: str, name: str) -> str:
    """Similarity of two values in [0, 1]; null if one is null."""
    if t.kind in ("jaccard", "contain"):
        x, y = words(a, name), words(b, name)
        both, either = _common(x, y, name)
        size = "size" if name == "spark" else "len"
        if t.kind == "contain":
            return f"cast({both} as double) / nullif(least({size}({x}), {size}({y})), 0)"
        return f"cast({both} as double) / nullif({either}, 0)"
    if t.kind == "lev":
        return f"1 - cast(levenshtein({a}, {b}) as double) / nullif(greatest(length({a}), length({b})), 0)"
    if t.kind == "digits":
        return f"case when regexp_extract({a}, '[0-9]+', 0) = regexp_extract({b}, '[0-9]+', 0) then 1.0e0 when {a} is null or {b} is null then null else 0.0e0 end"
    if t.kind == "exact":
        return f"case when {a} = {b} then 1.0e0 when {a} is null or {b} is null then null else 0.0e0 end"
    if t.kind == "absgap":
        return f"greatest(0.0e0, 1 - abs({a} - {b}) / {t.scale}e0)"
    if t.kind == "relgap":
        return f"greatest(0.0e0, 1 - abs({a} - {b}) / ({t.scale}e0 * nullif(greatest(abs({a}), abs({b})), 0)))"
    raise ValueError(t.kind)


def overall(w: Workload, name: str) -> str:
    """Weighted mean over attributes that neither side lacks, of columns a_<name> and b_<name>, to 6 digits."""
    sims = [(t, f"s_{t.name}") for t in w.attributes]
    top = " + ".join(f"coalesce({t.weight}e0 * {s}, 0.0e0)" for t, s in sims)
    low = " + ".join(f"case when {s} is null then 0.0e0 else {t.weight}e0 end" for t, s in sims)
    return f"coalesce(round(({top}) / nullif({low}, 0), 6), 0.0e0)"
