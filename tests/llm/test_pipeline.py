"""The corpus pipeline against brute force, stage by stage, and on rows that are odd."""

import re
from collections import Counter

import pytest
from pyspark.sql import functions as F

pytest.importorskip("corpus_pipeline")
import corpus_pipeline as pipeline

from slicegrad.llm import mixing, quality, secrets, simhash

from test_operators import ODD, SCHEMA, WORD, brute_quality, brute_targets

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """Some given documents, copies of some, odd rows, and rows again."""
    where = str(tmp_path_factory.mktemp("tables"))
    given = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select(*COLUMNS)
    words = F.split("text", " ")
    near = given.filter("doc_id < 20 and n_chars > 2500").select((F.col("doc_id") + 5000).alias("doc_id"), F.concat(F.lit("changed "), F.array_join(F.slice(words, 2, 100_000), " ")).alias("text"), "lang", "source", "n_chars")
    odd = spark.createDataFrame(ODD, SCHEMA).withColumn("doc_id", F.col("doc_id") + 9000)
    given.unionByName(near).unionByName(odd).unionByName(given.filter("doc_id = 3")).withColumn("extra", F.lit(1)).write.parquet(f"{where}/documents.parquet")
    return where


def rows(df):
    return [tuple(r) for r in df.select(*COLUMNS).collect()]


def test_stages_and_run(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    before = rows(docs)
    # quality: what fails the base rules goes; of the rest, as the posterior of the row's own votes says
    kept = pipeline.quality_rules(spark, docs, folder)
    scores = Counter((r["doc_id"], r["n_words"]) for r in quality.quality_scores(docs).filter("kept").collect())
    first = rows(kept)
    assert Counter((r[0], len(WORD.findall(r[1] or ""))) for r in first) == scores and not Counter(first) - Counter(before)
    assert not any(brute_quality(r[1])[-1] for r in first) and len(first) > 0.6 * len(before)
    # near-duplicates: a link is a distance within the limit of two whole fingerprints
    left = rows(pipeline.simhash_near_dedup(spark, kept, folder))
    bits = 48 * 16
    prints = [int.from_bytes(simhash.wide_fingerprint(r[1], bits), "big") for r in first]
    most = simhash.most_distance(bits, 0.8)
    root = list(range(len(first)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(first)):
        for j in range(i):
            if (prints[i] ^ prints[j]).bit_count() <= most:
                root[max(find(i), find(j))] = min(find(i), find(j))
    groups = Counter(find(i) for i in range(len(first)))
    assert not Counter(left) - Counter(first) and len(groups) <= len(left) <= 1.02 * len(groups)
    assert len({find(first.index(r)) for r in left}) == len(groups) < len(first)
    # secrets: what is left has no live-looking span, and nothing else changed
    second = spark.createDataFrame(left, SCHEMA)
    told = {(r["doc_id"]): r for r in secrets.secret_scan(second).collect()}
    clean = rows(pipeline.secret_scans(spark, second, folder))
    assert len(clean) == len(left)
    for old, new in zip(sorted(left, key=repr), sorted(clean, key=repr)):
        live = [s for s in told[old[0]]["spans"] if not s["copied"]]
        if not live:
            assert new == old
        else:
            text, at = "", 0
            for s in live:
                if s["start"] >= at:
                    text += old[1][at : s["start"]] + "<secret>"
                at = max(at, s["end"])
            assert new[1] == text + old[1][at:] and new[4] == len(new[1])
    # mixing: every source near its target, each row whole and at most twice
    third = spark.createDataFrame(clean, SCHEMA)
    mixed = rows(pipeline.mix_sources(spark, third, folder))
    sizes, taken = Counter(), Counter()
    for r in clean:
        sizes[r[3]] += len(WORD.findall(r[1] or ""))
    for r in mixed:
        taken[r[3]] += len(WORD.findall(r[1] or ""))
    for s, target in brute_targets(dict(sizes)).items():
        largest = max(len(WORD.findall(r[1] or "")) for r in clean if r[3] == s)
        assert abs(taken[s] - target) <= 2 * largest + 0.1 * target
    have = Counter(clean)
    assert all(n <= 2 * have[r] for r, n in Counter(mixed).items())
    # tokens: of every row of the mix, and what the whole run returns
    import public_tokenizers as P
    import tiktoken

    from slicegrad.llm.bpe import read_ranks

    theirs = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=read_ranks(P.path("byte_bpe_multi_50k.tiktoken")), special_tokens={})
    last = pipeline.run(spark, folder)
    assert last.columns == ["doc_id", "lang", "source", "ids"]
    want = Counter((r[0], r[2], r[3], tuple(theirs.encode_ordinary(r[1] or ""))) for r in mixed)
    assert Counter((r["doc_id"], r["lang"], r["source"], tuple(r["ids"])) for r in last.collect()) == want


def test_empty_table(spark, tmp_path):
    spark.createDataFrame([], SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    assert pipeline.run(spark, str(tmp_path)).count() == 0


def test_stages_are_the_ones_asked_for():
    assert [name for name, _ in pipeline.STAGES] == ["quality rules", "SimHash near-dedup", "secret scans", "mixing sources", "byte-level BPE"]
    assert re.search("nulls", pipeline.__doc__, re.I) and mixing.__doc__
