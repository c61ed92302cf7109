"""The registered queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from spanfold.llm.common import load, ship


def op7_simhash(spark, sf_dir):
    """Fingerprint and component of every document, at 2 or fewer differing bits."""
    from spanfold.llm.simhash import near_duplicates

    return near_duplicates(load(spark, sf_dir, "documents"))


def op9_window_dedup(spark, sf_dir):
    """Every document without the windows of 50 words that an earlier one has."""
    from spanfold.llm.window_dedup import remove_repeated_windows

    return remove_repeated_windows(load(spark, sf_dir, "documents"))


def op1_mixing(spark, sf_dir):
    """How many words of each document a mix of the sources to their targets takes."""
    from spanfold.llm.mixing import mixed_sizes

    return mixed_sizes(load(spark, sf_dir, "documents"))


def op2_suffix_dedup(spark, sf_dir):
    """Every document without the 50-byte strings that an earlier one has."""
    from spanfold.llm.suffix_dedup import remove_repeated_bytes

    return remove_repeated_bytes(load(spark, sf_dir, "documents"))


def op3_decontam(spark, sf_dir):
    """Documents that hold a benchmark item's template."""
    from spanfold.llm.decontam import contaminated

    return contaminated(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"))


def op4_langid(spark, sf_dir):
    """Language of every document; learned outside the held-out third."""
    from spanfold.llm.langid import identify

    return identify(load(spark, sf_dir, "documents"))


def op5_license_scan(spark, sf_dir):
    """License notices in every document."""
    from spanfold.llm.license_scan import scan_licenses

    return scan_licenses(load(spark, sf_dir, "documents"))


def op6_warc(spark, sf_dir):
    """Every page written as a WARC record and read back."""
    from spanfold.llm.warc import read_archives, write_archives

    target, manifest = write_archives(load(spark, sf_dir, "pages"))
    return read_archives(target, manifest).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op8_toxicity(spark, sf_dir):
    """Toxicity of every document; learned outside the held-out fifth."""
    from spanfold.llm.toxicity import classify

    return classify(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"))


def op10_ann(spark, sf_dir):
    """The 20 nearest vectors of every twentieth one."""
    from pyspark.sql import functions as F

    from spanfold.llm.ann import nearest

    return nearest(load(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


def queries() -> dict:
    return {name: f for name, f in globals().items() if name.startswith("op")}


def _cut_sql(unit: str) -> str:
    """Removed runs and kept pieces of sequences of n symbols from starts of repeated windows of 50:
    hits (doc_id, s) and seqs (doc_id, n, …) to kept (doc_id, n_removed, n_spans, joined)."""
    return f"""
marked as (select doc_id, s, case when s <= lag(s) over w + 50 then 0 else 1 end as opens from hits window w as (partition by doc_id order by s)),
runs as (select doc_id, min(s) as a, max(s) + 50 as b from (select *, sum(opens) over (partition by doc_id order by s) as run from marked) group by doc_id, run),
sides as (select doc_id, lag(b, 1, 0) over w as x, a as y from runs window w as (partition by doc_id order by a)
  union all select q.doc_id, coalesce(max(b), 0), any_value(n) from seqs q left join runs using (doc_id) group by q.doc_id),
kept as (select doc_id, coalesce(string_agg({unit} order by x) filter (where x < y), '') as joined from sides join seqs using (doc_id) group by doc_id),
cuts as (select doc_id, sum(b - a) as n_removed, count(*) as n_spans from runs group by doc_id)"""


# bytes as pairs of hexadecimal digits; strings are told apart by 128-bit digests
_OP2 = f"""
with seqs as (select doc_id, octet_length(encode(coalesce(text, ''))) as n, hex(coalesce(text, '')) as body from documents),
grams as (select doc_id, s, md5_number(substr(body, cast(2 * s + 1 as int), 100)) as g from (select doc_id, body, unnest(range(n - 49)) as s from seqs where n >= 50)),
hits as (select doc_id, s from (select doc_id, s, min(doc_id) over (partition by g) as least from grams) where least < doc_id), {_cut_sql("substr(body, cast(2 * x + 1 as int), cast(2 * (y - x) as int)), ''")}
select doc_id, cast(n as bigint) as n_bytes, cast(coalesce(n_removed, 0) as bigint) as n_removed, cast(coalesce(n_spans, 0) as bigint) as n_spans, sha256(unhex(joined)) as kept_sha256
from seqs join kept using (doc_id) left join cuts using (doc_id)"""

_OP6 = """
with p as (select page_id, coalesce(html, '') as body, max(page_id) over (partition by coalesce(html, '')) as last from pages),
h as (select *, list_transform(range(8), lambda g: cast('0x' || substr(sha1(body), cast(5 * g + 1 as int), 5) as bigint)) as parts from p)
select page_id, cast(octet_length(encode(body)) as bigint) as payload_bytes,
  array_to_string(list_transform(range(32), lambda k: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', cast(((parts[k // 4 + 1] >> (15 - 5 * (k % 4))) & 31) + 1 as int), 1)), '') as payload_digest,
  case when page_id = last then 'response' else 'revisit' end as record_type, case when page_id <> last then last end as refers_to from h"""

_OP9 = f"""
with seqs as (select doc_id, len(words) as n, words from (select doc_id, regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') as words from documents)),
grams as (select doc_id, s, md5_number(array_to_string(words[s + 1 : s + 50], ' ')) as g from (select doc_id, words, unnest(range(n - 49)) as s from seqs where n >= 50)),
hits as (select doc_id, s from (select doc_id, s, min(doc_id) over (partition by g) as least from grams) where least < doc_id), {_cut_sql("array_to_string(words[x + 1 : y], ' '), ' '")}
select doc_id, cast(n as bigint) as n_words, cast(coalesce(n_removed, 0) as bigint) as n_removed, sha256(joined) as kept_sha256, cast(coalesce(n_spans, 0) as bigint) as n_spans
from seqs join kept using (doc_id) left join cuts using (doc_id)"""


def oracle_sql() -> dict[str, str]:
    """SQL of the queries that SQL can express; the others are tested against brute force."""
    return {"op2_suffix_dedup": _OP2, "op6_warc": _OP6, "op9_window_dedup": _OP9}


ship(__name__)
