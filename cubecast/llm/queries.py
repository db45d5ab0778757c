"""The registered queries of the corpus operators, and the SQL of those that SQL can express."""

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import mixing, quality, topk_search, url_rules
from .exact_dedup import duplicate_classes
from .jaccard_join import linked_documents
from .pieces import round_trip
from .substring_dedup import repeated_words
from .suffix_dedup import repeated_bytes
from .tables import read
from .token_counts import count_tokens

COUNTED_WITH = "word_bpe_49k.json"
ENCODED_WITH = "piece_bpe_32k.model"


def op1_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linked_documents(read(spark, sf_dir, "documents"))


def op2_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    scorer, _ = quality.trained(docs)
    return quality.judged(docs, scorer)


def op3_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk_search.top_k(read(spark, sf_dir, "embeddings"), F.col("id") % 20 == 0)


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_words(read(spark, sf_dir, "documents"))


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return duplicate_classes(read(spark, sf_dir, "documents"))


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_bytes(read(spark, sf_dir, "documents"))


def op7_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(read(spark, sf_dir, "documents"))


def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_rules.judged(read(spark, sf_dir, "pages"), url_rules.RULES)


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(read(spark, sf_dir, "documents"), public_tokenizers.path(COUNTED_WITH))


def op10_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip(read(spark, sf_dir, "documents"), public_tokenizers.path(ENCODED_WITH))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_jaccard_join, op2_quality_classifier, op3_exact_topk, op4_substring_dedup, op5_exact_dedup, op6_suffix_dedup, op7_source_mixing, op8_url_filter, op9_token_counts, op10_pieces)}

ORACLES: dict[str, str] = {
    "op1_jaccard_join": r"""
with recursive w as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as t from documents),
s as (select distinct doc_id, key from (
  select doc_id, array_to_string(t[i + 1:i + 4], ' ') as key from (select doc_id, t, unnest(range(greatest(1, len(t) - 3))) as i from w where len(t) > 0))),
n as (select doc_id, count(*) as n from s group by doc_id),
p as (select a.doc_id as x, b.doc_id as y, count(*) as c from s a join s b on a.key = b.key and a.doc_id < b.doc_id group by 1, 2),
l as (select x, y from p join n a on a.doc_id = x join n b on b.doc_id = y where 100 * c >= 85 * (a.n + b.n - c)),
e as (select x, y from l union all select y, x from l),
r as (select doc_id as d, doc_id as z from w union select r.d, e.y from r join e on e.x = r.z)
select w.doc_id, coalesce(n.n, 0) as n_shingles, c.component_id from w left join n on n.doc_id = w.doc_id join (select d, min(z) as component_id from r group by d) c on c.d = w.doc_id
""",
    "op3_exact_topk": topk_search.ORACLE,
    "op4_substring_dedup": r"""
with w as (select doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as t from documents),
p as (select doc_id, t, unnest(range(len(t) - 12)) as i from w where len(t) >= 13),
k as (select doc_id, i, array_to_string(t[i + 1:i + 13], ' ') as key from p),
m as (select key, min(doc_id) as least from k group by key),
gone as (select distinct doc_id, i + j as pos from (select k.doc_id, k.i, unnest(range(13)) as j from k join m on k.key = m.key and m.least < k.doc_id)),
each_word as (select doc_id, unnest(t) as word, unnest(range(len(t))) as pos from w),
kept as (select e.doc_id, string_agg(e.word, ' ' order by e.pos) as text, count(*) as n from each_word e anti join gone g on g.doc_id = e.doc_id and g.pos = e.pos group by e.doc_id)
select w.doc_id, len(w.t) as n_words, len(w.t) - coalesce(kept.n, 0) as n_removed, sha256(coalesce(kept.text, '')) as kept_sha256 from w left join kept on kept.doc_id = w.doc_id
""",
    "op5_exact_dedup": r"""
select doc_id, first_value(doc_id) over w as keep_id, count(*) over (partition by plain) as group_size,
       doc_id = first_value(doc_id) over w as kept, sha256(plain) as text_sha256
from (select doc_id, coalesce(text, '') as text, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') as plain from documents)
window w as (partition by plain order by length(text) desc, doc_id)
""",
    "op6_suffix_dedup": r"""
with w as (select doc_id, hex(encode(coalesce(text, ''))) as h from documents),
k as (select doc_id, i, substr(h, 2 * i + 1, 100) as key from (select doc_id, h, unnest(range(length(h) // 2 - 49)) as i from w where length(h) >= 100)),
m as (select key, min(doc_id) as least from k group by key),
hit as (select k.doc_id, k.i from k join m on k.key = m.key and m.least < k.doc_id),
edge as (select *, case when i <= max(i) over (partition by doc_id order by i rows between unbounded preceding and 1 preceding) + 50 then 0 else 1 end as new from hit),
span as (select doc_id, min(i) as a, max(i) + 50 as b from (select *, sum(new) over (partition by doc_id order by i) as g from edge) group by doc_id, g),
gap as (select doc_id, a, b, coalesce(lag(b) over (partition by doc_id order by a), 0) as prior, lead(a) over (partition by doc_id order by a) as nxt from span),
cut as (select w.doc_id, sum(b - a) as n, count(*) as spans, string_agg(substr(h, 2 * prior + 1, 2 * (a - prior)) || case when nxt is null then substr(h, 2 * b + 1) else '' end, '' order by a) as kept from gap join w on w.doc_id = gap.doc_id group by w.doc_id)
select w.doc_id, length(h) // 2 as n_bytes, coalesce(cut.n, 0)::bigint as n_removed, coalesce(cut.spans, 0) as n_spans, sha256(unhex(coalesce(cut.kept, h))) as kept_sha256
from w left join cut on cut.doc_id = w.doc_id
""",
    "op7_source_mixing": mixing.ORACLE,
    "op8_url_filter": url_rules.oracle(),
}
