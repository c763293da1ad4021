"""Secret scans with corpus-wide ownership frequency, in DataFrame and SQL functions only.

Patterns find candidate spans. A candidate's value is hashed, and the hashes are aggregated over the corpus by
distinct repositories and distinct owners: a value that stands in several of both is a copied example, a value that
keeps to one owner looks live. Ownership decides which spans of the method are reported: those of known shapes unless
they are widely copied, and strings of no known shape but much variety (``owned``) only if a single owner has them.
The base kinds are always reported; of all, ``n_live`` counts those that are not widely copied. Counting goes by
(value, repository, owner) first, so a value that a third of the rows hold is combined before it moves.

The owner is a column, or else whom the text names: the domain of its first mail address, else its repository.

Null texts count as empty: no spans. Null repositories and owners count as one of their own. Repeated rows are each
reported, and count once for their repository. Other columns stay; an empty table gives an empty result. Positions
are code points, ends exclusive. Equal rows are redacted alike.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slicegrad.llm.common import cut, text_or_empty, whole_rows

#: Fixed values of the contract, in its order: kind, pattern, group of the value, least length of that group.
BASE_KINDS = [
    ("assign", r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8),
    ("access", r"AKIA[A-Z0-9]+", 0, 16),
    ("hex", r"[0-9a-f]{32,}", 0, 32),
]
#: Kinds of this method, and what a text with one contains.
MORE_KINDS = [
    ("private_key", r"-----BEGIN [A-Z ]*PRIVATE KEY-----([A-Za-z0-9+/=\s:,-]*?-----END [A-Z ]*PRIVATE KEY-----|[A-Za-z0-9+/=\s]*)", 0, 0, "PRIVATE KEY-----"),
    ("signed_token", r"eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]*", 0, 0, "eyJ"),
    ("forge_token", r"gh[pousr]_[A-Za-z0-9]{20,}", 0, 0, "gh"),
    ("chat_token", r"xox[abprs]-[A-Za-z0-9-]{10,}", 0, 0, "xox"),
    ("payment_key", r"[sr]k_live_[A-Za-z0-9]{10,}", 0, 0, "k_live_"),
    ("url_login", r"[A-Za-z][A-Za-z0-9+.-]{1,20}://[^\s/:@]{1,100}:[^\s/:@]{1,100}@", 0, 0, "://"),
]
#: Strings of no known shape: letters and digits, many of them different.
OWNED_KIND = ("owned", r"[A-Za-z0-9+/_=-]{24,}", 0, 24)
OWNED_VARIETY = 10
MAIL_DOMAIN = r"[A-Za-z0-9._%+-]+@([A-Za-z0-9.-]+\.[A-Za-z]{2,})"
KINDS = [k[0] for k in BASE_KINDS] + [k[0] for k in MORE_KINDS] + [OWNED_KIND[0]]
OWNED = len(KINDS) - 1
SPAN = "struct<start:int,kind:int,end:int,value:string>"
COMMON_REPOS = 3
COMMON_OWNERS = 3


def none() -> Column:
    return F.expr(f"cast(array() as array<{SPAN}>)")


def spans_of(text: Column, kind: int, pattern: str, group: int, least: int) -> Column:
    """The kind's spans: what stands between matches gives their places."""
    zipped = F.arrays_zip(F.split(text, pattern, -1).alias("gap"), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("hit"), F.regexp_extract_all(text, F.lit(pattern), F.lit(group)).alias("value"))

    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + F.length(x["gap"])
        end = start + F.length(x["hit"])
        span = F.struct(start.alias("start"), F.lit(kind).alias("kind"), end.alias("end"), x["value"].alias("value"))
        added = F.when(F.length(x["value"]) >= least, F.concat(acc["out"], F.array(span))).otherwise(acc["out"])
        return F.when(x["hit"].isNull(), acc).otherwise(F.struct(end.alias("at"), added.alias("out")))

    named = zipped.cast("array<struct<gap:string,hit:string,value:string>>")
    return F.aggregate(named, F.struct(F.lit(0).alias("at"), none().alias("out")), step, lambda acc: acc["out"])


def with_spans(rows: DataFrame) -> DataFrame:
    """``_text`` becomes never null; ``spans`` holds all spans by start, then kind."""
    ready = rows.withColumn("_text", text_or_empty(F.col("_text")))
    text = F.col("_text")
    found = [F.when(text.rlike(p), spans_of(text, k, p, g, n)).otherwise(none()) for k, (_, p, g, n) in enumerate(BASE_KINDS)]
    found += [F.when(text.contains(mark) & text.rlike(p), spans_of(text, len(BASE_KINDS) + k, p, g, n)).otherwise(none()) for k, (_, p, g, n, mark) in enumerate(MORE_KINDS)]
    known = ready.withColumn("spans", F.array_sort(F.concat(*found)))
    _, pattern, group, least = OWNED_KIND
    some = F.filter(spans_of(F.col("_text"), OWNED, pattern, group, least), lambda s: varied(s["value"]) & ~F.exists("spans", lambda k: (k["start"] < s["end"]) & (s["start"] < k["end"])))
    return known.withColumn("spans", F.when(F.col("_text").rlike(pattern), F.array_sort(F.concat("spans", some))).otherwise(F.col("spans")))


def varied(value: Column) -> Column:
    """Has letters and digits, and ``OWNED_VARIETY`` different characters."""
    return value.rlike("[0-9]") & value.rlike("[A-Za-z]") & (F.size(F.array_distinct(F.split(value, ""))) >= OWNED_VARIETY)


def owner_of(text: Column, repo: Column) -> Column:
    named = F.lower(F.regexp_extract(text, MAIL_DOMAIN, 1))
    return F.when(text.contains("@") & (named != ""), named).otherwise(repo.cast("string"))


def listed(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def value_hash(value: Column) -> Column:
    return F.xxhash64(value, F.lit("secret"))


def ownership(found: DataFrame, repos: int = COMMON_REPOS, owners: int = COMMON_OWNERS) -> DataFrame:
    """``found``: (spans, _repo, _owner). (hash, copied, single) of every value: stands it in as many repositories and owners at least, has it one owner."""
    each = found.select(F.explode("spans").alias("s"), "_repo", "_owner").select(value_hash(F.col("s.value")).alias("hash"), "_repo", "_owner")
    owned = each.groupBy("hash", "_repo", "_owner").agg(F.lit(1).alias("one"))
    # countDistinct leaves nulls out; a flag counts them as one
    def kinds(c: str) -> Column:
        return F.countDistinct(c) + F.max(F.col(c).isNull().cast("int"))

    counted = owned.groupBy("hash").agg(kinds("_repo").alias("r"), kinds("_owner").alias("o"))
    return counted.select("hash", ((F.col("r") >= repos) & (F.col("o") >= owners)).alias("copied"), (F.col("o") == 1).alias("single"))


def owned_rows(docs: DataFrame, text: str, repo: str, owner: str | None, **more: str) -> DataFrame:
    rows = whole_rows(docs, text, _repo=repo, **({"_owner": owner} if owner else {}), **more)
    return rows if owner else rows.withColumn("_owner", owner_of(F.col("_text"), F.col("_repo")))


def judged_spans(some: DataFrame, key: str, owned: DataFrame) -> DataFrame:
    """(key, spans) to (key, spans): each span with ``copied``, those that ownership withholds left out; none, no row."""
    each = some.select(key, F.explode("spans").alias("s")).withColumn("hash", value_hash(F.col("s.value"))).join(owned, "hash")
    base, shaped = F.col("s.kind") < len(BASE_KINDS), F.col("s.kind") < OWNED
    told = each.filter(base | (shaped & ~F.col("copied")) | (~shaped & F.col("single")))
    return told.groupBy(key).agg(F.array_sort(F.collect_list(F.struct("s.start", "s.kind", "s.end", "copied"))).alias("spans"))


def secret_scan(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", repo: str = "source", owner: str | None = None, **limits) -> DataFrame:
    """``doc_id``, ``spans`` (start, kind, end, copied), ``n_live`` (spans whose value is not widely copied) for every row."""
    rows = owned_rows(docs, text, repo, owner, doc_id=doc_id).drop("_row")
    found = cut(with_spans(rows).select("doc_id", "_repo", "_owner", "spans")).withColumn("_n", F.monotonically_increasing_id())
    some = found.filter(F.size("spans") > 0)
    told = judged_spans(some, "_n", ownership(some, **limits))
    empty = F.expr("cast(array() as array<struct<start:int,kind:int,end:int,copied:boolean>>)")
    listed_ = some.join(told.withColumnRenamed("spans", "told"), "_n", "left").select("doc_id", F.coalesce("told", empty).alias("spans"))
    every = listed_.unionByName(found.filter(F.size("spans") == 0).select("doc_id", empty.alias("spans")))
    return every.withColumn("n_live", F.size(F.filter("spans", lambda s: ~s["copied"])).cast("long"))


def redact_secrets(docs: DataFrame, text: str = "text", repo: str = "source", owner: str | None = None, mark: str = "<secret>", length: str | None = None, **limits) -> DataFrame:
    """``docs`` with every live-looking span replaced by ``mark``; the column ``length`` follows the text.

    Patterns are sought once; rows and spans are stored, so that each row keeps its number. Only rows with candidates
    are joined; the others go through as they are.
    """
    held = cut(with_spans(owned_rows(docs, text, repo, owner)).select("_row", "_repo", "_owner", "spans")).withColumn("_n", F.monotonically_increasing_id())
    some = held.filter(F.size("spans") > 0)
    told = judged_spans(some.select("_n", "spans"), "_n", ownership(some, **limits))
    live = told.select("_n", F.filter("spans", lambda s: ~s["copied"]).alias("live")).filter(F.size("live") > 0)
    joined = some.join(live, "_n", "left").withColumn("_text", text_or_empty(F.col("_row").getField(text)))

    def step(acc: Column, s: Column) -> Column:
        gap = F.substring(F.col("_text"), acc["at"] + 1, s["start"] - acc["at"])
        inside = s["start"] < acc["at"]
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.when(inside, acc["out"]).otherwise(F.concat(acc["out"], gap, F.lit(mark))).alias("out"))

    done = F.aggregate("live", F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), step, lambda acc: F.concat(acc["out"], F.substring(F.col("_text"), acc["at"] + 1, F.length("_text"))))
    hit = F.col("live").isNotNull()
    redacted = joined.withColumn("_new", F.when(hit, done).otherwise(F.col("_row").getField(text)))
    changed = {text: F.col("_new")} | ({length: F.when(hit, F.length("_new").cast(docs.schema[length].dataType)).otherwise(F.col("_row").getField(length))} if length in docs.columns else {})
    out = redacted.select(*[changed.get(c, F.col("_row").getField(c)).alias(c) for c in docs.columns])
    return out.unionByName(held.filter(F.size("spans") == 0).select(*[F.col("_row").getField(c).alias(c) for c in docs.columns]))
