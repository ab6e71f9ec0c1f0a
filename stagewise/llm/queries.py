"""The ten queries of this package, with production parameters over whole tables, and their SQL."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stagewise.llm import (
    exact_naming,
    host_reputation,
    html_extract,
    line_spread,
    minhash,
    mixing,
    packing,
    quality_cnn,
    toxicity,
    vector_forest,
)


def _read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path() -> str:
    """The tokenizer file of the box, or what STAGEWISE_TOKENIZER names."""
    own = os.environ.get("STAGEWISE_TOKENIZER")
    if own:
        return own
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op1_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main text of every page: (page_id, url, text, n_chars)."""
    return html_extract.extract(_read(spark, sf_dir, "pages"))


def op2_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of documents whose two-word shingles agree to 0.8: (doc_id, n_shingles, component_id, kept)."""
    found = minhash.near_duplicates(_read(spark, sf_dir, "documents"), width=2)
    return found.select("doc_id", "n_shingles", "component_id", "kept")


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality of every document, learned from labels that are not held out: (doc_id, held_out, score, predicted)."""
    return quality_cnn.score(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "labels"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity of every document: (doc_id, a probability per category, toxic, rejected)."""
    return toxicity.score(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "labels"))


def page_outcomes(pages: DataFrame, labels: DataFrame) -> DataFrame:
    """(host, good): the quality label of the document that the last number of a page's path names."""
    path = host_reputation.path_of(F.col("url"))
    number = F.regexp_extract(path, r"([0-9]{1,18})(?:\.html)?/?$", 1)
    told = pages.select(host_reputation.host_of(F.col("url")).alias("host"), F.when(number != "", number.cast("long")).alias("doc_id"))
    return told.join(labels.select("doc_id", F.col("quality").alias("good")), "doc_id").select("host", "good")


def op5_host_reputation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A verdict on every page's url: (page_id, host, path, rule, verdict)."""
    pages = _read(spark, sf_dir, "pages")
    found = host_reputation.judge(pages, page_outcomes(pages, _read(spark, sf_dir, "labels")))
    return found.select("page_id", "host", "path", "rule", "verdict")


def op6_vector_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of vectors with a cosine of 0.9 or more: (vec_id, n_links, component_id, kept)."""
    return vector_forest.near_vectors(_read(spark, sf_dir, "embeddings"))


def op7_line_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document without the lines that ten sites or more show: (doc_id, n_lines, n_removed, n_chars, text_md5)."""
    found = line_spread.remove_boilerplate(_read(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_lines", "n_removed", F.length("text").cast("long").alias("n_chars"), F.md5(F.encode("text", "UTF-8")).alias("text_md5"))


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's tokens in windows of 4,096: (doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset)."""
    return packing.pack(_read(spark, sf_dir, "documents"), tokenizer_path())


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every showing of a document in the mix of all sources: (doc_id, source, tokens, pass, passes, block, position)."""
    plan = mixing.plan_mix(_read(spark, sf_dir, "documents"))
    return plan.select("doc_id", "source", "tokens", "pass", "passes", "block", "position")


def op10_exact_naming(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with the one of its equals that stays: (doc_id, keep_id, group_size, kept, text_sha256)."""
    return exact_naming.exact_duplicates(_read(spark, sf_dir, "documents"))


def queries() -> dict:
    return {f.__name__: f for f in (
        op1_html_extraction, op2_minhash, op3_quality, op4_toxicity, op5_host_reputation, op6_vector_forest,
        op7_line_spread, op8_packing, op9_mixing, op10_exact_naming,
    )}


_OP10 = """
with n as (select doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as t from documents)
select doc_id, max(doc_id) over (partition by t) as keep_id, count(*) over (partition by t) as group_size,
       doc_id = max(doc_id) over (partition by t) as kept, sha256(t) as text_sha256
from n
"""

_OP7 = """
with l as (
  select doc_id, source, s.pos as pos, s.line as raw, trim(s.line, ' ') as line
  from (select doc_id, source, unnest([{'pos': i, 'line': x[i]} for i in range(1, len(x) + 1)]) as s
        from (select doc_id, source, string_split(coalesce(text, ''), chr(10)) as x from documents))),
bad as (select line, min(doc_id) as first from l where line <> '' group by line having count(distinct source) >= 10),
m as (select l.*, b.line is not null and l.doc_id <> b.first as gone from l left join bad b on l.line = b.line)
select doc_id, count(*) as n_lines, count(*) filter (where gone) as n_removed,
       length(coalesce(string_agg(raw, chr(10) order by pos) filter (where not gone), '')) as n_chars,
       md5(coalesce(string_agg(raw, chr(10) order by pos) filter (where not gone), '')) as text_md5
from m group by doc_id
"""


#: The largest repetition allowed is 1.5, so the smallest source's passes give the exponent in closed form.
_OP9 = """
with d as (
  select doc_id, source, length(t) - length(replace(t, ' ', '')) + 1 as tokens,
         cast('0x' || substr(md5('1|' || coalesce(source, '') || '|' || coalesce(cast(doc_id as varchar), '') || '|' || md5(coalesce(text, ''))), 1, 15) as bigint) as rank
  from (select *, translate(coalesce(text, ''), chr(10), ' ') as t from documents)),
t as (select source, sum(tokens)::double as total from d group by source),
e as (select case when max(total) > min(total) then least(1.0, ln(1.5) / ln(max(total) / min(total))) else 1.0 end as power, max(total) as top from t),
b as (select source, total, pow(top / total, power) as p, floor(pow(top / total, power) + 1e-9) as whole from t, e),
c as (select source, total, whole, greatest(floor((p - whole) * total + 1e-6), 0) as room from b),
s as (select d.*, c.whole, c.whole + c.room / c.total as passes,
             c.whole + case when sum(tokens) over (partition by d.source order by rank range unbounded preceding) <= c.room then 1 else 0 end as times
      from d join c on d.source is not distinct from c.source),
n as (select greatest(1, ceil(sum(whole * total + room) / 262144)) as blocks from c),
x as (select *, (pass + rank / 1152921504606846976.0::double) / passes as place from (select *, unnest(range(0, times::bigint)) as pass from s)),
y as (select *, cast(least(floor(place * blocks), blocks - 1) as bigint) as block from x, n)
select doc_id, source, tokens, pass, cast(times as bigint) as passes, block, row_number() over (partition by block order by place, rank, coalesce(source, '')) - 1 as position
from y
"""


def _op5() -> str:
    """Counts and posteriors of the three levels, as the operator has them."""
    parts = ["""
u as (select page_id, url, case when instr(url, '://') > 0 then regexp_extract(url, '^.*?://([^/?#]*)', 1, 's') else '' end as raw_host,
      case when instr(url, '://') > 0 then regexp_extract(url, '^.*?://[^/?#]*([^?#]*)', 1, 's') else '' end as path from pages),
p as (select page_id, path, translate(coalesce(raw_host, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
      regexp_extract(path, '([0-9]{1,18})(?:\\.html)?/?$', 1) as number from u),
o as (select p.host, l.quality as good from p join labels l on l.doc_id = try_cast(p.number as bigint) where l.quality is not null),
h0 as (select host, count(*)::double as n, sum(good)::double as good from o group by host),
h as (select *, case when len(string_split(host, '.')) > 2 then list_aggregate(string_split(host, '.')[-2:], 'string_agg', '.') else host end as domain,
      string_split(host, '.')[-1] as suffix from h0),
m0 as (select (sum(good) + 1) / (sum(n) + 2) as mean from h)"""]
    above, on = "m0", ""
    for level, parent in (("suffix", None), ("domain", "suffix"), ("host", "domain")):
        keys = f"{parent}, {level}" if parent else level
        on = f"on g.{parent} = a.{parent}" if parent else "on true"
        parts.append(f"""
g_{level} as (select g.{level}, g.n, g.good, a.mean from (select {keys}, sum(n) as n, sum(good) as good from h group by {keys}) g join {above} a {on}),
s_{level} as (select least(greatest(coalesce(case when r > 0 then 1 / r - 1 end, 1000.0), 1.0), 1000.0) as s from
  (select sum(n * (good / n - mean) * (good / n - mean) - mean * (1 - mean)) / nullif(sum(mean * (1 - mean) * (n - 1)), 0) as r from g_{level})),
p_{level} as (select {level}, mean * s + good as a, (1 - mean) * s + n - good as b from g_{level}, s_{level}),
m_{level} as (select {level}, a, b, a / (a + b) as mean from p_{level})""")
        above = f"m_{level}"
    fits = lambda host, path: f"((p.host = '{host}' or ends_with(p.host, '.{host}')) and starts_with(p.path, '{path}'))"
    rules = sorted(host_reputation.RULES, key=lambda r: -len(r[0] + r[1]))
    text = " ".join(f"when {fits(h, s)} then '{h}{s}'" for h, s, _ in rules)
    verdict = " ".join(f"when {fits(h, s)} then '{v}'" for h, s, v in rules)
    return "with " + ",".join(parts) + f"""
select p.page_id, p.host, p.path, case {text} end as rule,
       case {verdict} when m.mean + 1.645 * sqrt(m.a * m.b / ((m.a + m.b) * (m.a + m.b) * (m.a + m.b + 1))) < 0.5 then 'block' else 'allow' end as verdict
from p left join m_host m on p.host = m.host
"""


def oracle_sql() -> dict[str, str]:
    return {"op10_exact_naming": _OP10, "op9_mixing": _OP9, "op7_line_spread": _OP7, "op5_host_reputation": _op5()}
