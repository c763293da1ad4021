"""The text operators as registered queries, each over its whole table."""

from __future__ import annotations

from pyspark.sql import functions as F

from slicegrad.llm import bpe, language, licenses, mixing, quality, secrets, simhash, toxicity, urls, vectors
from slicegrad.llm.common import table

SQL: dict[str, str] = {}


def _shrunk(name: str, source: str, keep: str) -> str:
    """The step of urls.shrunk as two common table expressions."""
    return f"""{name}_s AS (SELECT least(greatest(sum(prior * (1 - prior) * n) / sum(n) / greatest((sum(n * (bad / n - prior) * (bad / n - prior)) - sum(prior * (1 - prior))) / sum(n), 1e-4) - 1, 1), 200) AS strength FROM {source}),
  {name} AS (SELECT {keep}, (bad + strength * prior) / (n + strength) AS rate, n + strength AS weight FROM {source}, {name}_s)"""


_RULES = ", ".join(f"('{v}', '{h}', '{p}')" for v, h, p in urls.RULES)
_MARKS, _SUFFIX = "|".join(urls.HOST_MARKS), "|".join(x.replace(".", "\\.") for x in urls.SUFFIXES) + "|[^.]*"
_SOFT = "(greatest({0}, 0) + ln(1 + exp(-abs({0}))))"


def _risk(name: str, source: str, key: str) -> str:
    """The tail of the beta posterior, summed over the steps of urls.tail."""
    at = "(ln(a / b) + sqrt(1 / a + 1 / b) * k / 10.0)"
    weight = f"exp(-a * {_SOFT.format('(-t)')} - b * {_SOFT.format('t')} + a * {_SOFT.format('(-ln(a / b))')} + b * {_SOFT.format('(ln(a / b))')})"
    return f"""{name} AS (SELECT {key}, sum(CASE WHEN t > 0 THEN v ELSE 0 END) / sum(v) AS risk FROM (SELECT *, {weight} AS v FROM (SELECT *, {at} AS t FROM (SELECT {key}, greatest(least(rate, 1 - 1e-6), 1e-6) * weight AS a, (1 - greatest(least(rate, 1 - 1e-6), 1e-6)) * weight AS b FROM {source}), (SELECT unnest(range(-{urls.GRID}, {urls.GRID + 1})) AS k))) GROUP BY 1)"""


SQL["op9_url_filters"] = f"""WITH u AS (SELECT page_id, html, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
  h AS (SELECT page_id, html, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
  rules(verdict, rh, rp) AS (VALUES {_RULES}),
  fit AS (SELECT page_id, rh || rp AS rule, verdict FROM h JOIN rules ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp) QUALIFY row_number() OVER (PARTITION BY page_id ORDER BY len(rh || rp) DESC) = 1),
  p AS (SELECT page_id, host, path, rule, verdict, CASE WHEN verdict IS NOT NULL THEN verdict = 'block' WHEN regexp_matches(host, '{_MARKS}') THEN true
      WHEN coalesce(len(html), 0) > 0 THEN (len(html) - len(translate(html, '{urls.JUNK}', ''))) / len(html) > {urls.JUNK_SHARE} END AS bad,
    regexp_extract(host, '(?:^|\\.)((?:[^.]+\\.)?(?:{_SUFFIX}))$', 1) AS domain, regexp_extract(host, '(?:^|\\.)({_SUFFIX})$', 1) AS suffix FROM h LEFT JOIN fit USING (page_id)),
  hosts AS (SELECT host, domain, suffix, count(*)::DOUBLE AS n, sum(bad::INTEGER)::DOUBLE AS bad FROM p WHERE bad IS NOT NULL GROUP BY 1, 2, 3),
  l2 AS (SELECT suffix, sum(n) AS n, sum(bad) AS bad, (SELECT (coalesce(sum(bad), 0) + 1) / (coalesce(sum(n), 0) + 2) FROM hosts) AS prior FROM hosts GROUP BY 1), {_shrunk("s2", "l2", "suffix")},
  l1 AS (SELECT domain, suffix, sum(n) AS n, sum(bad) AS bad, any_value(s2.rate) AS prior FROM hosts JOIN s2 USING (suffix) GROUP BY 1, 2), {_shrunk("s1", "l1", "domain")},
  l0 AS (SELECT host, domain, suffix, n, bad, s1.rate AS prior FROM hosts JOIN s1 USING (domain)), {_shrunk("s0", "l0", "host, domain, suffix, strength")},
  d AS (SELECT domain, sum(rate * weight) / sum(weight) AS rate, max(strength) AS weight FROM s0 GROUP BY 1), x AS (SELECT suffix, sum(rate * weight) / sum(weight) AS rate, max(strength) AS weight FROM s0 GROUP BY 1),
  w AS (SELECT 0 AS one, sum(rate * weight) / sum(weight) AS rate, max(strength) AS weight FROM s0),
  {_risk("rh", "s0", "host")}, {_risk("rd", "d", "domain")}, {_risk("rx", "x", "suffix")}, {_risk("rw", "w", "one")}
  SELECT page_id, p.host, path, rule, coalesce(verdict, CASE WHEN coalesce(rh.risk, rd.risk, rx.risk, (SELECT risk FROM rw), 0) > {urls.SURE} THEN 'block' ELSE 'allow' END) AS verdict
  FROM p LEFT JOIN rh ON rh.host = p.host LEFT JOIN rd ON rd.domain = p.domain LEFT JOIN rx ON rx.suffix = p.suffix"""
SQL["op10_mix_sources"] = f"""WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size FROM documents),
  s AS (SELECT source, sum(size)::BIGINT AS source_size, count(*) AS n_rows FROM d GROUP BY 1),
  w AS (SELECT *, [3.0, 1.0, 2.0][1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3]::DOUBLE AS weight, source_size * 2.0::DOUBLE AS most FROM s),
  l AS (SELECT *, ((sum(source_size) OVER ())::DOUBLE * 1.5 - coalesce(sum(most) OVER (ORDER BY most / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / sum(weight) OVER (ORDER BY most / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM w),
  t AS (SELECT source, source_size, ceil(n_rows / {float(mixing.CHUNK_ROWS)})::BIGINT AS chunks, CASE WHEN level * weight >= most THEN most ELSE (SELECT max(level) FROM l WHERE level * weight < most) * weight END AS target FROM l),
  c AS (SELECT d.doc_id, d.source, size, source_size, target, ('0x' || substr(md5(concat_ws(':', '17', d.doc_id::VARCHAR, size::VARCHAR)), 1, 8))::BIGINT % chunks AS chunk FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
  k AS (SELECT *, row_number() OVER (PARTITION BY source ORDER BY chunk, size, doc_id NULLS LAST) AS k FROM c),
  x AS (SELECT *, ('0x' || substr(md5('17:' || coalesce(source, chr(0) || 'null')), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS o, CASE WHEN source_size > 0 THEN target / source_size ELSE 0 END AS r FROM k)
  SELECT doc_id, size, source_size, target, (size * (floor(o + r * k) - floor(o + r * (k - 1))))::BIGINT AS taken FROM x"""
SQL["op6_embedding_near_dedup"] = """WITH RECURSIVE e AS (SELECT vec_id, label, list_transform(embedding, lambda v: v::DOUBLE) AS x FROM embeddings),
  good AS (SELECT vec_id, label, x FROM e WHERE label IS NOT NULL AND len(x) > 0 AND len(list_filter(x, lambda v: v IS NULL OR NOT isfinite(v))) = 0 AND len(list_filter(x, lambda v: v <> 0)) > 0),
  links AS MATERIALIZED (SELECT a.vec_id AS a, b.vec_id AS b FROM good a JOIN good b ON a.label = b.label AND len(a.x) = len(b.x) AND a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.x, b.x) >= 0.93),
  reach AS (SELECT vec_id AS a, vec_id AS b FROM e UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a),
  c AS (SELECT a, min(b) AS component_id FROM reach GROUP BY 1)
  SELECT vec_id, (SELECT count(*) FROM links WHERE links.a = vec_id) AS n_links, component_id, vec_id = component_id AS kept FROM e JOIN c ON c.a = vec_id"""


def _spans_sql() -> str:
    """For each kind, matches with their places: the lengths of what stands before, added up."""
    parts = []
    for k, (_, pattern, group, least, *_) in enumerate([*secrets.BASE_KINDS, *secrets.MORE_KINDS, secrets.OWNED_KIND]):
        p = "'" + pattern.replace("'", "''") + "'"
        parts.append(f"""SELECT doc_id, source, owner, {k} AS kind, unnest(regexp_extract_all(text, {p}, 0)) AS hit, unnest(regexp_extract_all(text, {p}, {group})) AS value, unnest(string_split_regex(text, {p})[1:len(string_split_regex(text, {p})) - 1]) AS gap,
      unnest(range(1, len(regexp_extract_all(text, {p}, 0)) + 1)) AS nth, {least} AS least FROM d WHERE regexp_matches(text, {p})""")
    return " UNION ALL ".join(parts)


_KINDS = "[" + ", ".join(f"'{k}'" for k in secrets.KINDS) + "]"
_LISTED = "coalesce(string_agg({k}[kind + 1] || ':' || start || ':' || stop, ',' ORDER BY start, kind) {f}, '')"
_MAIL = secrets.MAIL_DOMAIN
SQL["op8_secret_scan"] = f"""WITH t AS (SELECT doc_id, source, coalesce(text, '') AS text FROM documents),
  d AS (SELECT *, CASE WHEN contains(text, '@') AND regexp_extract(text, '{_MAIL}', 1) <> '' THEN lower(regexp_extract(text, '{_MAIL}', 1)) ELSE source END AS owner FROM t), m AS ({_spans_sql()}),
  e AS (SELECT *, sum(len(gap) + len(hit)) OVER (PARTITION BY doc_id, kind ORDER BY nth) AS stop FROM m),
  f AS (SELECT doc_id, source, owner, kind, value, (stop - len(hit))::BIGINT AS start, stop::BIGINT AS stop FROM e WHERE len(value) >= least),
  s AS (SELECT * FROM f WHERE kind < {secrets.OWNED} OR regexp_matches(value, '[0-9]') AND regexp_matches(value, '[A-Za-z]') AND len(list_distinct(string_split(value, ''))) >= {secrets.OWNED_VARIETY}
    AND NOT EXISTS (SELECT 1 FROM f k WHERE k.doc_id = f.doc_id AND k.kind < {secrets.OWNED} AND k.start < f.stop AND f.start < k.stop)),
  o AS (SELECT value, count(DISTINCT source) + max((source IS NULL)::INTEGER) AS repos, count(DISTINCT owner) + max((owner IS NULL)::INTEGER) AS owners FROM s GROUP BY 1),
  j AS (SELECT s.*, repos >= {secrets.COMMON_REPOS} AND owners >= {secrets.COMMON_OWNERS} AS copied FROM s JOIN o USING (value) WHERE kind < 3 OR kind < {secrets.OWNED} AND NOT copied OR kind = {secrets.OWNED} AND owners = 1)
  SELECT d.doc_id, count(kind) FILTER (kind = 0) AS n_assign, count(kind) FILTER (kind = 1) AS n_access, count(kind) FILTER (kind = 2) AS n_hex,
    sha256({_LISTED.format(k=_KINDS, f="FILTER (WHERE kind < 3)")}) AS base_sha256, {_LISTED.format(k=_KINDS, f="FILTER (WHERE kind IS NOT NULL)")} AS spans,
    count(kind) FILTER (NOT copied) AS n_live
  FROM d LEFT JOIN j USING (doc_id) GROUP BY 1"""


def op1_byte_bpe(spark, sf_dir):
    import public_tokenizers

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    coded = bpe.bpe_encode(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN, carry=["doc_id"])
    return coded.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), F.sha2(F.array_join("ids", ","), 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op2_license_scan(spark, sf_dir):
    return licenses.license_scan(table(spark, sf_dir, "documents").select("doc_id", "text"), carry=["doc_id"])


def op3_simhash_near_dedup(spark, sf_dir):
    groups = simhash.simhash_groups(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return groups.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op4_quality_rules(spark, sf_dir):
    scored = quality.quality_scores(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return scored.select("doc_id", *quality.BASE, "base_failed", "kept", F.round("good", 6).alias("good"))


def op5_toxicity(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    labels = table(spark, sf_dir, "labels").select("doc_id", "toxic")
    model = toxicity.learn_toxicity(docs, labels.filter(language.fold(F.col("doc_id"), 4) != 2))
    rows = docs.select("doc_id", (language.fold(F.col("doc_id"), 4) == 2).alias("held_out"), "text")
    return toxicity.score_toxicity(rows, model, carry=["doc_id", "held_out"])


def op6_embedding_near_dedup(spark, sf_dir):
    return vectors.near_vectors(table(spark, sf_dir, "embeddings"))


def op7_language_id(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    dictionaries = language.learn_dictionaries(docs.filter(language.fold(F.col("doc_id"), 5) != 0))
    rows = docs.select("doc_id", (language.fold(F.col("doc_id"), 5) == 0).alias("held_out"), "text")
    return language.predict_language(rows, dictionaries, carry=["doc_id", "held_out"])


def op8_secret_scan(spark, sf_dir):
    found = secrets.secret_scan(table(spark, sf_dir, "documents").select("doc_id", "text", "source"))
    base = F.filter("spans", lambda s: s["kind"] < len(secrets.BASE_KINDS))
    kinds = F.transform("spans", lambda s: s["kind"])
    counts = [(F.size("spans") - F.size(F.array_remove(kinds, k))).cast("long").alias(f"n_{kind[0]}") for k, kind in enumerate(secrets.BASE_KINDS)]
    return found.select("doc_id", *counts, F.sha2(secrets.listed(base), 256).alias("base_sha256"), secrets.listed(F.col("spans")).alias("spans"), "n_live")


def op9_url_filters(spark, sf_dir):
    return urls.judge_urls(table(spark, sf_dir, "pages").select("page_id", "url", "html"), html="html").select("page_id", "host", "path", "rule", "verdict")


def op10_mix_sources(spark, sf_dir):
    mixed = mixing.mix_copies(table(spark, sf_dir, "documents").select("doc_id", "text", "source"), keep=False)
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def queries() -> dict:
    return {k: f for k, f in globals().items() if k.startswith("op") and callable(f)}


def oracle_sql() -> dict:
    return dict(SQL)
