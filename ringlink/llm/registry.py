"""The corpus operators' queries."""

from __future__ import annotations

from ringlink.llm import embeddings, licenses, mixing, packing, pii, quality_lm, rules, simhash, toxicity, warc
from ringlink.llm.common import table


def queries() -> dict:
    docs = lambda f: lambda spark, d: f(table(spark, d, "documents"))
    return {
        "op1_best_fit_packing": docs(packing.digest),
        "op2_channel_toxicity": lambda spark, d: toxicity.score(table(spark, d, "documents"), table(spark, d, "labels")),
        "op3_warc_transactions": lambda spark, d: warc.digest(table(spark, d, "pages")),
        "op4_license_containment": docs(licenses.digest),
        "op5_epsilon_grid_join": lambda spark, d: embeddings.near_duplicates(table(spark, d, "embeddings")),
        "op6_entropy_mixing": docs(mixing.digest),
        "op7_covering_simhash": docs(simhash.digest),
        "op8_bootstrapped_pii": docs(pii.digest),
        "op9_kneser_ney_quality": lambda spark, d: quality_lm.score(table(spark, d, "documents"), table(spark, d, "labels")),
        "op10_rule_ledger": docs(rules.digest),
    }


#: A text's words; a word of the rules is what ASCII white space parts.
_WORDS = "regexp_extract_all(coalesce(text,''),'[^\\x20\\x09-\\x0D]+')"

_RULES = f"""WITH d AS (SELECT row_number() OVER () AS id, doc_id, coalesce(text,'') AS t, {_WORDS} AS w FROM documents),
win AS (SELECT id, i, w[i]||' '||w[i+1]||' '||w[i+2] AS g FROM d, unnest(range(1,len(w)-1)) r(i) WHERE len(w)>=3),
rep AS (SELECT id, count(DISTINCT i+k) AS n FROM (SELECT id, i, count(*) OVER (PARTITION BY id, g) AS c FROM win), range(0,3) q(k) WHERE c>1 GROUP BY id),
ln AS (SELECT id, count(*) AS n, count(DISTINCT x) AS u FROM (SELECT id, unnest(string_split(t,chr(10))) AS x FROM d) WHERE regexp_matches(x,'[^\\x20\\x09-\\x0D]') GROUP BY id),
m AS (SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))),0)::BIGINT AS word_chars, len(regexp_extract_all(t,'[#*$%&|<>]'))::BIGINT AS n_symbols,
 (coalesce(ln.n,0)-coalesce(ln.u,0))::BIGINT AS n_dup_lines, coalesce(rep.n,0)::BIGINT AS n_repeat_words, coalesce(ln.n,0) AS n_lines FROM d LEFT JOIN rep USING (id) LEFT JOIN ln USING (id)),
f AS (SELECT *, (n_words<50)::BIGINT + 2*(100*n_repeat_words>50*n_words)::BIGINT + 4*(10*n_symbols>5*n_words)::BIGINT + 8*(n_lines>=4 AND 100*n_dup_lines>50*n_lines)::BIGINT
 + 16*(word_chars>20*n_words OR word_chars<2*n_words)::BIGINT + 32*(n_words<5)::BIGINT AS failures FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (failures & 3)<>0 AS base_failed, (failures & 31)=0 AS kept, failures FROM f"""

#: Base 32 of a digest: two hex digits a byte, five bits a letter.
_B32 = """array_to_string(list_transform(range(0,32), lambda k: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', ((('0x'||substr(h||'00',((k*5)//4+1)::INT,2))::BIGINT >> (3-(k*5)%4)) & 31)::INT+1, 1)),'')"""
_WARC = f"""WITH p AS (SELECT page_id, coalesce(html,'') AS t, sha1(coalesce(html,'')) AS h FROM pages), g AS (SELECT *, min(page_id) OVER (PARTITION BY h) AS first FROM p)
SELECT page_id, octet_length(encode(t))::BIGINT AS payload_bytes, {_B32} AS payload_digest, CASE WHEN page_id=first THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id<>first THEN first END AS refers_to FROM g"""

_EMBEDDINGS = """WITH RECURSIVE u AS (SELECT vec_id, label, embedding::DOUBLE[] AS v FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM u a JOIN u b ON a.label=b.label AND a.vec_id<>b.vec_id WHERE list_cosine_similarity(a.v,b.v)>=0.93),
r AS (SELECT vec_id AS a, vec_id AS b FROM u UNION SELECT r.a, l.b FROM r JOIN l ON r.b=l.a),
c AS (SELECT a, min(b) AS low FROM r GROUP BY a)
SELECT e.vec_id, (SELECT count(*) FROM l WHERE l.a=e.vec_id) AS n_links, coalesce(low, e.vec_id) AS component_id, coalesce(low, e.vec_id)=e.vec_id AS kept FROM embeddings e LEFT JOIN c ON c.a=e.vec_id"""


def oracle_sql() -> dict[str, str]:
    """DuckDB counterparts where SQL can express the whole result; the other operators are tested against brute force."""
    return {"op3_warc_transactions": _WARC, "op5_epsilon_grid_join": _EMBEDDINGS, "op10_rule_ledger": _RULES}
