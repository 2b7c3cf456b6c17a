"""Queries of this folder, for registration, and the SQL they are held against."""

from __future__ import annotations

from .lines import op5_line_dedup
from .mixing import op2_mixing
from .neardup import op4_minhash
from .packing import op6_packing
from .pii import op9_personal_data
from .quality import op3_quality
from .rules import op8_quality_rules
from .substring import op10_substring
from .toxicity import op1_toxicity
from .vectors import op7_vectors

QUERIES = {
    f.__name__: f
    for f in (op1_toxicity, op2_mixing, op3_quality, op4_minhash, op5_line_dedup, op6_packing, op7_vectors, op8_quality_rules, op9_personal_data, op10_substring)
}

_WORDS = r"regexp_extract_all({text}, '[^\x20\x09-\x0D]+')"
_REACH = """
rc as (select distinct a node, a r from lk union select case when rc.node = lk.a then lk.b else lk.a end, rc.r from rc join lk on rc.node = lk.a or rc.node = lk.b),
cm as (select node, min(r) c from rc group by 1)"""

ORACLES: dict[str, str] = {
    "op10_substring": f"""
with w as (select doc_id, {_WORDS.format(text="coalesce(text, '')")} ws from documents),
g as (select doc_id, i, array_to_string(ws[i:i + 12], ' ') k from w, unnest(range(1, len(ws) - 11)) t(i)),
f as (select k, min(doc_id) m from g group by 1),
c as (select distinct doc_id, i + j p from g join f using (k), range(0, 13) r(j) where m < doc_id),
n as (select doc_id, count(*) n from c group by 1),
x as (select doc_id, i p, ws[i] word from w, unnest(range(1, len(ws) + 1)) t(i)),
k as (select doc_id, string_agg(word, ' ' order by p) kept from x anti join c using (doc_id, p) group by 1)
select w.doc_id, len(ws)::bigint n_words, coalesce(n, 0)::bigint n_removed, sha256(coalesce(kept, '')) kept_sha256
from w left join n using (doc_id) left join k using (doc_id)""",
    "op4_minhash": f"""
with recursive w as (select doc_id, {_WORDS.format(text="translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')")} ws from documents),
s as (select distinct doc_id, case when len(ws) = 1 then ws[1] else ws[i] || ' ' || ws[i + 1] end k from w, unnest(range(1, greatest(len(ws), 2))) t(i) where len(ws) > 0),
n as (select doc_id, count(*) n from s group by 1),
p as (select x.doc_id a, y.doc_id b, count(*) m from s x join s y on x.k = y.k and x.doc_id < y.doc_id group by 1, 2),
lk as (select a, b from p join n na on na.doc_id = a join n nb on nb.doc_id = b where 100 * m >= 80 * (na.n + nb.n - m)
  union all select doc_id, doc_id from documents), {_REACH}
select doc_id, coalesce(n, 0)::bigint n_shingles, c component_id, doc_id = c kept from documents left join n using (doc_id) join cm on node = doc_id""",
    "op7_vectors": f"""
with recursive v as (select vec_id, label, embedding::double[] v from embeddings where label is not null and embedding is not null
  and len(list_filter(embedding, lambda x: x is null or isnan(x) or isinf(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0),
d as (select x.vec_id a, y.vec_id b from v x join v y on x.label = y.label and x.vec_id < y.vec_id where list_cosine_similarity(x.v, y.v) >= 0.98),
lk as (select a, b from d union all select vec_id, vec_id from embeddings), {_REACH},
n as (select id, count(*) n from (select a id from d union all select b from d) group by 1)
select vec_id, coalesce(n, 0)::bigint n_links, c component_id, vec_id = c kept from embeddings left join n on id = vec_id join cm on node = vec_id""",
}
