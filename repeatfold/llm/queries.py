"""The queries of this subpackage and their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from repeatfold.llm import license_scan, mixing, near_dup, ngram_join, packing, quality, substring_dedup, token_count, topk, url_filter
from repeatfold.llm.common import table

URL_RULES = [("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/")]


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    return url_filter.judge(pages.select("page_id", "url"), URL_RULES, url_filter.link_edges(pages)).select("page_id", "host", "path", "rule", "verdict")


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.dedup(table(spark, sf_dir, "documents").select("doc_id", "text"), with_text=False)


def op3_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.similar_components(table(spark, sf_dir, "documents"))


def op4_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "sentence_ids", "n_sentences", "licenses")


def op5_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality.score(docs, quality.train(docs, table(spark, sf_dir, "labels")))


def op6_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return topk.search(vectors, vectors.where("vec_id % 100 = 0"))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = packing.pack(table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"), with_ids=False)
    return packing.as_sequences(pieces).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "bucket")


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Calibrated rate and copies in the sample of each document."""
    return mixing.calibrate(table(spark, sf_dir, "documents")).select("doc_id", "n_tokens", F.round("rate", 6).alias("rate"), "copies")


def op8_mixing_marginals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Wanted, expected and reached token shares of the sample."""
    return mixing.marginals(mixing.calibrate(table(spark, sf_dir, "documents")))


def op8_mixing_violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Targets of categories that occur whose expected share is off by more than 0.005."""
    off = F.abs(F.col("wanted") - F.col("expected")) > mixing.CLOSE
    return op8_mixing_marginals(spark, sf_dir).where("wanted is not null").agg(F.sum(off.cast("long")).alias("violations"))


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_count.count_tokens(table(spark, sf_dir, "documents"), tokenizer_path("piece_bpe_32k.model"))


def op10_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(table(spark, sf_dir, "embeddings"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_url_filter": op1_url_filter,
        "op2_substring_dedup": op2_substring_dedup,
        "op3_ngram_join": op3_ngram_join,
        "op4_license_scan": op4_license_scan,
        "op5_quality_classifier": op5_quality_classifier,
        "op6_topk_search": op6_topk_search,
        "op7_packing": op7_packing,
        "op8_mixing": op8_mixing,
        "op8_mixing_marginals": op8_mixing_marginals,
        "op8_mixing_violations": op8_mixing_violations,
        "op9_token_counts": op9_token_counts,
        "op10_near_duplicates": op10_near_duplicates,
    }


def url_filter_sql(source: str = "pages") -> str:
    """Verdicts with the components by plain recursion over the edges."""
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    q = lambda s: "'" + s.replace("'", "''") + "'"
    rules = ", ".join(f"('{a}', '{h}', '{p}', '{h + p}')" for a, h, p in URL_RULES)
    head = lambda c: f"regexp_extract({c}, '(?s)^(.*?://[^/?#]*)', 1)"
    node = lambda c: f"case when {head(c)} <> '' then translate({head(c)}, '{upper}', '{lower}') || regexp_extract({c}, '(?s)^.*?://[^/?#]*([^#]*)', 1) end"
    low_host = lambda c: f"translate(coalesce(regexp_extract({c}, '(?s)^.*?://([^/?#]*)([^?#]*)', 1), ''), '{upper}', '{lower}')"
    path = lambda c: f"coalesce(regexp_extract({c}, '(?s)^.*?://([^/?#]*)([^?#]*)', 2), '')"
    parts = lambda c: f"{low_host(c)} as host, {path(c)} as path"
    judged = lambda t, key: f"select {key}, arg_max(struct_pack(rule := rule, action := action), (length(rule) * 2 + (action = 'allow')::int)) as hit from {t} join rules on (host = h or ends_with(host, '.' || h)) and starts_with(path, p) group by all"
    folder = "regexp_extract(url, '(?s)^(.*?://[^/?#]*(?:/[^?#]*/|/)?)', 1)"
    tags = lambda tag, part: f"list_transform(regexp_extract_all(coalesce(html, ''), {q(tag)}), lambda x: regexp_extract(x, {q(part)}, 1))"
    return f"""
with recursive rules(action, h, p, rule) as (values {rules}),
page as (select row_number() over () as r, page_id, url, html, {parts('url')} from {source}),
shorter as (select url, 'https://' || regexp_replace(host, {q(url_filter.FIRST_LABEL)}, '') || regexp_replace(path, {q(url_filter.PAGE_END)}, '') as t,
  array_to_string(list_filter(string_split(regexp_extract(url, '(?s)^.*?://[^?#]*\\?([^#]*)', 1), '&'), lambda x: x <> '' and not regexp_matches(x, {q(url_filter.TRACKING)})), '&') as kept from page where contains(url, '://')),
targets as (select url, regexp_replace(unnest(list_concat({tags(url_filter.CANONICAL, url_filter.HREF)}, {tags(url_filter.REFRESH, url_filter.TARGET)})), '&(?:amp|#38|#[xX]26);', '&', 'g') as t from page where contains(url, '://')),
resolved as (select url as f, case when regexp_matches(t, {q(url_filter.SCHEME + '//')}) then t when regexp_matches(t, {q(url_filter.SCHEME)}) then null when starts_with(t, '//') then regexp_extract(url, '(?s)^(.*?:)//', 1) || t
  when starts_with(t, '/') then {head('url')} || t when starts_with(t, '?') then regexp_extract(url, '(?s)^([^?#]*)', 1) || t when starts_with(t, '#') then url
  else {folder} || case when ends_with({folder}, '/') then '' else '/' end || t end as t from targets where t <> ''),
split as (select f, t, {path('t')} as p, list_transform(string_split({path('t')}, '/')[2:], lambda x: [x]) as s from resolved where t is not null),
flat as (select f, t, p, list_reduce(list_prepend([]::varchar[], s), lambda a, x: case x[1] when '..' then a[:-2] when '.' then a else list_concat(a, x) end) as s from split),
clean as (select f, {head('t')} || case when contains(p, '/.') then '/' || array_to_string(case when regexp_matches(p, '/\\.\\.?$') then list_append(s, '') else s end, '/') else p end || regexp_extract(t, '(?s)^.*?://[^/?#]*[^?#]*(.*)$', 1) as t from flat),
links as (select {node('f')} as f, {node('t')} as t from (from clean union all select url, t || case when kept <> '' then '?' || kept else '' end from shorter)),
edges as (select f, t from links where f <> t union select t, f from links where f <> t),
reach(n, m) as (select f, f from edges union select e.t, reach.m from reach join edges e on e.f = reach.n),
comp as (select n, min(m) as c from reach group by n),
nodes as (select n, c, {parts('n')} from comp),
node_hits as ({judged('nodes', 'n, c')}),
votes as (select c, bool_or(hit.action = 'allow') as a from node_hits group by c),
said as (select n, case when a then 'allow' else 'block' end as said from comp join votes using (c)),
hits as ({judged('page', 'r')})
select page_id, host, path, hit.rule as rule, coalesce(hit.action, said, 'allow') as verdict
from page left join hits using (r) left join said on said.n = {node('url')}"""


def topk_sql() -> str:
    return """
with v as (select vec_id, list_transform(embedding, lambda x: floor(1024 * x::double)::bigint) as e from embeddings
  where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0),
q as (select * from v where vec_id % 100 = 0),
s as (select q.vec_id as query_id, c.vec_id, list_sum(list_transform(list_zip(q.e, c.e), lambda z: z[1] * z[2]))::bigint as score from q join v c on c.vec_id <> q.vec_id and len(c.e) = len(q.e)),
r as (select *, row_number() over (partition by query_id order by score desc, vec_id)::int as rank from s)
select query_id, rank, vec_id, score from r where rank <= 10"""


def near_duplicates_sql() -> str:
    return """
with recursive v as materialized (select row_number() over () as r, vec_id, list_transform(embedding, lambda x: x::double) as e,
  embedding is not null and len(embedding) > 0 and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0 as ok from embeddings),
u as materialized (select r, vec_id, e, sqrt(list_sum(list_transform(e, lambda x: x * x))) as n from v where ok),
l as materialized (select a.r as a, b.r as b, b.vec_id as w from u a join u b on a.r <> b.r and len(a.e) = len(b.e) where list_sum(list_transform(list_zip(a.e, b.e), lambda z: z[1] * z[2])) / (a.n * b.n) >= 0.9),
reach(a, w) as (select r, vec_id from v union select l.a, reach.w from reach join l on l.b = reach.a),
comp as (select a, min(w) as c from reach group by a),
links as (select a, count(*) as n from l group by a)
select vec_id, coalesce(n, 0)::bigint as n_links, c as component_id, vec_id = c as kept from v join comp on comp.a = r left join links on links.a = r"""


def oracle_sql() -> dict[str, str]:
    return {
        "op1_url_filter": url_filter_sql(),
        "op4_license_scan": license_scan.scan_sql(),
        "op6_topk_search": topk_sql(),
        "op8_mixing": mixing.calibrate_sql(),
        "op8_mixing_violations": "select 0::bigint as violations",
        "op10_near_duplicates": near_duplicates_sql(),
    }
