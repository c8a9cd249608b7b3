"""The matching workloads: two record collections and the truth, by arithmetic on keys of the given tables.

Queries are SQL that Spark and other engines read alike; what differs between dialects stands in <...>.
Twin ids are ten times the key, distractors one or two more.
"""

from __future__ import annotations

from dataclasses import dataclass, field

SWAPPED = "concat(substr({0}, instr({0}, ' ') + 1), ' ', substr({0}, 1, instr({0}, ' ') - 1))"
JITTER = "(1 + cast(({0} * 37) % 11 - 5 as double) / 1000)"
#: Dialects: Spark, and the SQL of the oracles.
MACROS = {
    "spark": {"<day>": "datediff(cast(o_orderdate as date), date '1970-01-01')", "<title>": "regexp_extract(html, '<title>([^<]*)</title>', 1)", "<host>": "regexp_extract(url, '://([^/]+)', 1)", "<path>": "regexp_extract(url, '://[^/]+(/[^?#]*)', 1)", "<lang>": "regexp_extract(html, 'lang=\"([a-z]+)\"', 1)", "<nodigits>": "regexp_replace(url, '[0-9]+', '7')", "<nofragment>": "regexp_replace(regexp_replace(lower(url), '#.*$', ''), '://m[.]', '://')", "<five>": "array_join(slice(split(title, ' '), 1, 5), ' ')", "<twothree>": "array_join(slice(split(title, ' '), 2, 2), ' ')"},
    "oracle": {"<day>": "datediff('day', date '1970-01-01', cast(o_orderdate as date))", "<title>": "regexp_extract(html, '<title>([^<]*)</title>', 1)", "<host>": "regexp_extract(url, '://([^/]+)', 1)", "<path>": "regexp_extract(url, '://[^/]+(/[^?#]*)', 1)", "<lang>": "regexp_extract(html, 'lang=\"([a-z]+)\"', 1)", "<nodigits>": "regexp_replace(url, '[0-9]+', '7', 'g')", "<nofragment>": "regexp_replace(regexp_replace(lower(url), '#.*$', ''), '://m[.]', '://')", "<five>": "array_to_string(list_slice(string_split(title, ' '), 1, 5), ' ')", "<twothree>": "array_to_string(list_slice(string_split(title, ' '), 2, 3), ' ')"},
}


def dialect(text: str, name: str) -> str:
    for k, v in MACROS[name].items():
        text = text.replace(k, v)
    return text


@dataclass(frozen=True)
class Attribute:
    """A column of both collections, how it is compared, its weight, and a scale where it needs one."""

    name: str
    kind: str
    weight: float = 1.0
    scale: float = 1.0


@dataclass(frozen=True)
class Workload:
    key: str
    d1: str
    d2: str
    truth: str
    attributes: tuple[Attribute, ...]
    blocked_on: tuple[str, ...]
    tokens: str = "word"
    max_df: float = 0.25
    tau: float = 0.9
    order: int = field(default=0)
    #: Percent of the union of their grams that documents of the truth share, where it is made of grams.
    overlap: int = 0


def _part(cols: str) -> str:
    return f"select p_partkey as rid, {cols} from {{part}}"


_name = f"case when p_partkey % 3 = 0 then {SWAPPED.format('p_name')} else p_name end as name"
_brand = "case when p_partkey % 5 = 0 then concat('B', substr(p_brand, 7)) else p_brand end as brand"
_price = f"p_retailprice * {JITTER.format('p_partkey')} as price"
_type = "case when p_partkey % 7 = 0 then cast(null as string) else p_type end as type"
_cust = "select c_custkey as rid, c_name as name, n_name as nation, r_name as region, c_acctbal as balance, c_mktsegment as segment from {customer} join {nation} on c_nationkey = n_nationkey join {region} on n_regionkey = r_regionkey"
_order = "select o_orderkey as rid, c_name as customer, <day> as day, o_totalprice / 1000 as price, o_orderpriority as priority from {orders} join {customer} on o_custkey = c_custkey"
_page = "select page_id as rid, url, <host> as host, <path> as path, <lang> as lang, <title> as title, cast(length(html) as double) as size from {pages}"
_offer = f"""select o.rid, {_name.replace('p_partkey', 'k')}, {_brand.replace('p_partkey', 'k')}, p_type as type, cast(p_size as double) as size, p_retailprice * {JITTER.format('k')} as price, n_name as nation
 from (select distinct l_partkey as k, l_suppkey as s, 1000000 * l_partkey + l_suppkey as rid from {{lineitem}} where l_linenumber <= 2) o
 join {{part}} on k = p_partkey join {{supplier}} on s = s_suppkey join {{nation}} on s_nationkey = n_nationkey
 left join (select l_partkey as bk, min(l_suppkey) as best from {{lineitem}} where l_linenumber <= 2 group by l_partkey) b on bk = k
 where k % 3 = 0 or s <> best"""
_best = "select l_partkey as bk, min(l_suppkey) as best from {lineitem} where l_linenumber <= 2 group by l_partkey"
_doc = "select doc_id as rid, text, lang, source, cast(n_chars as double) as n_chars from {documents}"

WORKLOADS = {
    w.key: w
    for w in (
        Workload(
            "w1", _part("p_name as name, p_brand as brand, p_retailprice as price"),
            f"select 10 * p_partkey as rid, {_name}, {_brand}, {_price} from {{part}}",
            "select p_partkey as anchor_id, 10 * p_partkey as cand_id from {part}",
            (Attribute("name", "jaccard", 2), Attribute("brand", "digits", 2), Attribute("price", "relgap", 1, 0.02)), ("name", "brand"),
        ),
        Workload(
            "w2", _part("p_name as name, p_brand as brand, p_type as type, cast(p_size as double) as size"),
            f"select 10 * p_partkey as rid, {_name}, {_brand}, {_type}, cast(p_size as double) as size from {{part}} where p_partkey % 4 <> 3"
            " union all select 10 * p_partkey + 1, p_name, p_brand, p_type, cast(p_size + 1 as double) from {part}"
            " union all select 10 * p_partkey + 2, p_name, p_brand, case when p_type = 'SMALL' then 'LARGE' else 'SMALL' end, cast(p_size as double) from {part} where p_partkey % 2 = 0",
            "select p_partkey as anchor_id, 10 * p_partkey as cand_id from {part} where p_partkey % 4 <> 3",
            (Attribute("name", "jaccard", 3), Attribute("brand", "digits", 2), Attribute("type", "exact", 1), Attribute("size", "absgap", 2, 3.0)), ("name", "brand", "type", "size"),
        ),
        Workload(
            "w3", f"{_doc} where doc_id % 2 = 0", f"{_doc} where doc_id % 2 = 1",
            "select a.rid as anchor_id, b.rid as cand_id from {documents_grams} a join {documents_grams} b on a.gram = b.gram where a.rid % 2 = 0 and b.rid % 2 = 1"
            " group by a.rid, b.rid having count(*) >= 0.3 * (max(a.n) + max(b.n) - count(*))",
            (Attribute("text", "jaccard", 4), Attribute("lang", "exact", 1), Attribute("n_chars", "relgap", 1, 1.0)), ("text",), max_df=0.02, tau=0.6, overlap=30,
        ),
        Workload(
            "w4", "select item_id as rid, text from {benchmark}", "select doc_id as rid, text from {documents}",
            "select item_id as anchor_id, doc_id as cand_id from {benchmark} b join {documents} d on contains(d.text, b.text)",
            (Attribute("text", "contain", 1),), ("text",), max_df=0.02, tau=0.8,
        ),
        Workload(
            "w5", _cust,
            f"select 10 * rid as rid, concat(substr(name, 1, 16), substr(name, 18, 1), substr(name, 17, 1)) as name, nation, region, floor(balance) as balance, segment from ({_cust}) c where rid % 8 in (0, 3, 6)"
            f" union all select 10 * (rid + 1000000) as rid, name, nation, region, balance + 57, segment from ({_cust}) c where rid % 8 not in (0, 3, 6)",
            "select c_custkey as anchor_id, 10 * c_custkey as cand_id from {customer} where c_custkey % 8 in (0, 3, 6)",
            (Attribute("name", "lev", 3), Attribute("nation", "exact", 1), Attribute("region", "exact", 1), Attribute("balance", "relgap", 2, 0.05), Attribute("segment", "exact", 1)), ("name", "nation", "segment", "balance"), tokens="qgram3",
        ),
        Workload(
            "w6", f"select * from ({_order}) o where rid % 10 = 0",
            f"select 10 * rid as rid, customer, day + cast(rid % 3 as int) as day, price * {JITTER.format('rid')} as price, priority from ({_order}) o where rid % 50 = 0"
            f" union all select 10 * rid as rid, customer, day, price, priority from ({_order}) o where rid % 10 <> 0",
            "select o_orderkey as anchor_id, 10 * o_orderkey as cand_id from {orders} where o_orderkey % 50 = 0",
            (Attribute("customer", "digits", 2), Attribute("day", "absgap", 2, 30.0), Attribute("price", "relgap", 2, 0.05), Attribute("priority", "exact", 1)), ("customer", "priority"),
        ),
        Workload(
            "w7", _page,
            f"select 10 * rid as rid, <nofragment> as url, host, path, lang, <five> as title, size from ({_page}) p where rid % 11 in (0, 5)"
            f" union all select 10 * rid + 1 as rid, <nodigits> as url, host, concat(path, '7') as path, lang, <twothree> as title, size + 999 from ({_page}) p",
            "select page_id as anchor_id, 10 * page_id as cand_id from {pages} where page_id % 11 in (0, 5)",
            (Attribute("url", "lev", 2), Attribute("host", "exact", 1), Attribute("path", "exact", 1), Attribute("lang", "exact", 1), Attribute("title", "jaccard", 2), Attribute("size", "relgap", 1, 0.1)), ("url", "title"), tau=0.8,
        ),
        Workload(
            "w8", f"select p_partkey as rid, p_name as name, p_brand as brand, p_type as type, cast(p_size as double) as size, p_retailprice as price, n_name as nation from {{part}} join ({_best}) b on bk = p_partkey join {{supplier}} on s_suppkey = best join {{nation}} on s_nationkey = n_nationkey",
            _offer, f"select bk as anchor_id, 1000000 * bk + best as cand_id from ({_best}) b where bk % 3 = 0",
            (Attribute("name", "jaccard", 2), Attribute("brand", "digits", 2), Attribute("type", "exact", 1), Attribute("size", "absgap", 2, 3.0), Attribute("price", "relgap", 1, 0.02), Attribute("nation", "exact", 2)), ("name", "brand", "type", "size", "nation"),
        ),
    )
}

#: The words stand in a generated row of their own, else the optimizer puts their expression into the lambda, to run once a gram.
#: Distinct 5-word grams of documents with their number, for the truth of w3 and w9.
GRAMS = {
    "spark": r"select rid, gram, size(grams) as n from (select doc_id as rid, array_distinct(transform(sequence(1, greatest(size(w) - 4, 1)), i -> concat_ws(' ', slice(w, i, 5)))) as grams from (select doc_id, w from {documents} lateral view explode(array(filter(split(lower(text), '[^\\pL\\pN]+'), t -> t <> ''))) x as w) t) g lateral view explode(grams) e as gram",
    "oracle": r"select rid, unnest(grams) as gram, len(grams) as n from (select doc_id as rid, list_distinct(list_transform(range(1, greatest(len(w) - 4, 1) + 1), lambda i: array_to_string(list_slice(w, i, i + 4), ' '))) as grams from (select doc_id, list_filter(string_split_regex(lower(text), '[^\pL\pN]+'), lambda t: t <> '') as w from documents) t) g",
}
#: Hashes of the words that GRAMS are made of, in order.
WORD_HASHES = r"transform(filter(split(lower(text), '[^\\pL\\pN]+'), t -> t <> ''), t -> xxhash64(t))"
