"""Quality rules under weak supervision, in DataFrame and SQL functions only.

Each rule votes good (1), bad (-1) or abstains (0). Expectation-maximisation over the table of vote patterns
(at most 3 ** rules rows, whatever the input) estimates how often a rule says what of good and of bad
documents; the posterior probability of good then decides, in place of all rules having to pass.

Null and empty texts have no words: every count is 0 and they fail the base rules. Repeated rows are judged
alike; the rows' other columns and null ids pass through; an empty table gives an empty result.
Words of repeated 5-word windows are found by the windows' 64-bit hashes inside one text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slicegrad.llm.common import cut, single_spaced, text_or_empty, whole_rows

SYMBOLS = "#*$%&|<>"
BASE = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
ROUNDS = 30


def measured(rows: DataFrame) -> DataFrame:
    """Replace ``_text`` by the counts that the rules look at; the other columns stay."""
    rest = [c for c in rows.columns if c != "_text"]
    text = text_or_empty(F.col("_text"))
    without = text
    for c in SYMBOLS:
        without = F.replace(without, F.lit(c), F.lit(""))
    has_word = r"[^\x20\x09-\x0D]"
    a = rows.select(
        *rest,
        F.length(text).alias("n_chars"),
        (F.length(text) - F.length(without)).cast("long").alias("n_symbols"),
        (F.length(text) - F.length(F.replace(text, F.lit("!"), F.lit("")))).alias("n_calls"),
        F.filter(F.split(text, "\n"), lambda x: x.rlike(has_word)).alias("lines"),
        single_spaced(text).alias("spaced"),
    )
    b = a.select(
        *rest, "n_symbols", "n_calls",
        F.size("lines").alias("n_lines"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.length(F.replace("spaced", F.lit(" "), F.lit(""))).cast("long").alias("word_chars"),
        F.when(F.col("spaced") == "", F.expr("cast(array() as array<string>)")).otherwise(F.split("spaced", " ")).alias("words"),
    )
    five = F.transform(F.sequence(F.lit(0), F.size("words") - 5), lambda i: F.xxhash64(*[F.get("words", i + k) for k in range(5)]))
    c = b.select(
        *rest, "n_symbols", "n_calls", "n_lines", "n_dup_lines", "word_chars",
        F.size("words").cast("long").alias("n_words"),
        F.size(F.array_distinct("words")).alias("n_distinct"),
        F.size(F.filter("words", lambda w: (F.length(w) > 1) & (F.upper(w) == w) & (F.lower(w) != w))).alias("n_shouted"),
        F.size(F.filter("words", lambda w: w.rlike("[#*$%&|<>]"))).alias("n_marked"),
        F.when(F.size("words") >= 5, five).otherwise(F.expr("cast(array() as array<bigint>)")).alias("windows"),
    )
    pairs = F.transform("windows", lambda h, i: F.struct(h.alias("h"), i.alias("i")))
    d = c.select(
        *[x for x in c.columns if x != "windows"],
        F.when(F.size(F.array_distinct("windows")) < F.size("windows"), F.array_sort(pairs)).otherwise(F.expr("cast(array() as array<struct<h:bigint,i:int>>)")).alias("sorted"),
    )
    repeated = F.filter("sorted", lambda x, k: F.coalesce((k > 0) & (F.get("sorted", k - 1)["h"] == x["h"]), F.lit(False)) | F.coalesce(F.get("sorted", k + 1)["h"] == x["h"], F.lit(False)))
    covered = F.aggregate(
        F.array_sort(F.transform(repeated, lambda x: x["i"])),
        F.struct(F.lit(0).cast("long").alias("n"), F.lit(-5).alias("last")),
        lambda acc, p: F.struct((acc["n"] + F.least(F.lit(5), p - acc["last"])).alias("n"), p.alias("last")),
        lambda acc: acc["n"],
    )
    return d.select(*[x for x in d.columns if x != "sorted"], covered.alias("n_repeat_words"))


def rules() -> dict[str, Column]:
    """Name to vote, over the columns of ``measured``."""
    n = F.greatest(F.col("n_words"), F.lit(1))

    def vote(bad: Column, good: Column) -> Column:
        return F.when(bad, -1).when(good, 1).otherwise(0)

    length, symbols, repeats = F.col("word_chars") / n, F.col("n_symbols") / n, F.col("n_repeat_words") / n
    shouted, calls, distinct = F.col("n_shouted") / n, F.col("n_calls") / n, F.col("n_distinct") / n
    doubled = F.col("n_dup_lines") / F.greatest(F.col("n_lines"), F.lit(1))
    return {
        "long_enough": vote(F.col("n_words") < 10, F.col("n_words") >= 30),
        "word_length": vote((length < 2) | (length > 14), length.between(3, 11)),
        "symbols": vote(symbols > 0.2, symbols < 0.05),
        "symbol_share": vote(F.col("n_symbols") > 0.04 * F.col("word_chars"), F.col("n_symbols") < 0.01 * F.col("word_chars")),
        "marked_words": vote(F.col("n_marked") > 0.15 * n, F.col("n_marked") < 0.05 * n),
        "lines": vote(doubled > 0.5, doubled < 0.2),
        "repeats": vote(repeats > 0.2, repeats < 0.1),
        "shouting": vote(shouted > 0.5, shouted < 0.2),
        "calls": vote(calls > 0.3, calls < 0.1),
        "variety": vote((distinct < 0.2) & (F.col("n_words") < 400), distinct > 0.35),
    }


def fit_votes(votes: DataFrame) -> DataFrame:
    """``votes``: an array column of that name. Returns (votes, good): each pattern's posterior."""
    patterns = votes.groupBy("votes").agg(F.count(F.lit(1)).cast("double").alias("c"))
    # patterns stand in order, so that sums come out alike in every run; a first guess: one bad vote outweighs the good ones, as in all-must-pass filtering; the rounds then weigh each rule
    start = "1 / (1 + exp(-(1 + aggregate(votes, 0D, (a, v) -> a + if(v < 0, -4D, 0.3D * v)))))"
    gathered = patterns.agg(F.array_sort(F.collect_list(F.struct("votes", "c", F.expr(start).alias("q")))).alias("p"))
    weight = "aggregate(p, cast(0 as double), (a, x) -> a + x.c * {0})"
    # counts by rule and vote, with a hundredth of the weight as prior belief that rules are right 9 times in 10
    table = """transform(sequence(0, coalesce(size(get(p, 0).votes), 1) - 1), j -> transform(array(-1, 0, 1), v -> named_struct(
        'g', aggregate(p, 0.01D * w * case v when 1 then 0.6D when 0 then 0.3D else 0.1D end, (a, x) -> a + if(x.votes[j] = v, x.c * x.q, 0D)),
        'b', aggregate(p, 0.01D * w * case v when 1 then 0.1D when 0 then 0.3D else 0.6D end, (a, x) -> a + if(x.votes[j] = v, x.c * (1 - x.q), 0D)))))"""
    odds = "transform(t, r -> transform(r, y -> ln(y.g / (r[0].g + r[1].g + r[2].g)) - ln(y.b / (r[0].b + r[1].b + r[2].b))))"
    # one-element arrays bind a value once, else every use in a lambda would compute it again
    step = f"""aggregate(array({table}), p, (q0, t) -> aggregate(array({odds}), q0, (q1, o) -> transform(q1, x -> named_struct('votes', x.votes, 'c', x.c,
        'q', 1 / (1 + exp(-(pr + aggregate(sequence(0, size(x.votes) - 1), 0D, (a, j) -> a + o[j][x.votes[j] + 1]))))))))"""
    bound = f"aggregate(array(named_struct('w', {weight.format('1')}, 'g', {weight.format('x.q')})), p, (p0, k) -> {step.replace('0.01D * w', '0.01D * greatest(k.w, 1D)').replace('pr +', 'ln((k.g + 1) / (k.w - k.g + 1)) +')})"
    fitted = gathered.filter("size(p) > 0").selectExpr(f"aggregate(sequence(1, {ROUNDS}), p, (p, i) -> {bound}) as p")
    return fitted.select(F.explode("p").alias("x")).select(F.col("x.votes").alias("votes"), F.col("x.q").alias("good"))


def judged(rows: DataFrame, fitted: DataFrame, least: float = 0.5) -> DataFrame:
    """``rows`` with ``votes``, and ``good``, ``base_failed`` and ``kept``; patterns are at most 3 ** rules rows, so they are broadcast."""
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    # one expression over both sides of the join: a filter on it stays above, where the counts are columns already,
    # and is not pushed below the projections that would have to compute them again inside their lambdas
    kept = F.coalesce(F.when(~failed, F.col("good")), F.lit(0.0)) >= least
    return rows.join(F.broadcast(fitted), "votes", "left").withColumn("base_failed", failed).withColumn("kept", kept)


def with_votes(rows: DataFrame) -> DataFrame:
    return measured(rows).withColumn("votes", F.array(*rules().values()))


def quality_scores(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``doc_id``, the base counts, ``votes``, ``good``, ``base_failed``, ``kept`` for every row."""
    rows = cut(with_votes(whole_rows(docs, text, doc_id=doc_id).select("doc_id", "_text")).select("doc_id", *BASE, "votes"))
    return judged(rows, cut(fit_votes(rows)))


def quality_filter(docs: DataFrame, text: str = "text") -> DataFrame:
    """The rows of ``docs`` that are kept. Votes are cast twice, so no text is shuffled or stored."""
    rows = whole_rows(docs, text)
    fitted = cut(fit_votes(with_votes(rows.select("_text")).select("votes")))
    kept = judged(with_votes(rows), fitted).filter("kept")
    return kept.select(*[F.col("_row").getField(c).alias(c) for c in docs.columns])
