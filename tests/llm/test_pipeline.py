"""The pipeline stage by stage against brute-force versions of each stage's decision."""

import hashlib
import re

import public_tokenizers
import pytest

import corpus_pipeline
from sieve.llm import bpe, mixing

from .test_operators import brute_components, brute_quality, brute_substrings

SMALL = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    out = [docs]
    for k, (_, f) in enumerate(corpus_pipeline.STAGES):
        path = str(tmp_path_factory.mktemp("stages") / str(k))
        f(spark, out[-1], SMALL).write.parquet(path)
        out.append(spark.read.parquet(path))
    return out


def test_columns_stay(stages):
    assert all(x.columns == stages[0].columns for x in stages[:-1])


def test_quality_stage(stages):
    kept = {r["doc_id"] for r in stages[1].collect()}
    for r in stages[0].collect():
        n, chars, symbols, dup, rep = brute_quality(r["text"])
        lines = len([x for x in (r["text"] or "").split("\n") if WORD.search(x)])
        bad = n < 10 or 100 * rep > 20 * n or 100 * symbols > 25 * n or 100 * dup > 40 * lines or chars < 2 * n or chars > 20 * n
        assert (r["doc_id"] in kept) == (not bad)


def test_near_dedup_stage(stages):
    rows = [(r["doc_id"], r["text"]) for r in stages[1].collect()]
    want = {i for i, _, c in brute_components(rows, 5) if i == c}
    assert {str(r["doc_id"]) for r in stages[2].collect()} == want


def test_substring_stage(stages):
    before = [(r["doc_id"], r["text"]) for r in stages[2].collect()]
    after = {r["doc_id"]: r for r in stages[3].collect()}
    for line in brute_substrings(before):
        i, n, gone, kept = eval(line)
        if n == gone:
            assert i not in after
        else:
            assert after[i]["text"].split() == kept.split() and after[i]["n_chars"] == len(after[i]["text"])


def test_mixing_stage(stages):
    words = lambda rows: {s: sum(len((r["text"] or "").split()) for r in rows if r["source"] == s) for s in {r["source"] for r in rows}}
    before, after = words(stages[3].collect()), words(stages[4].collect())
    names = sorted(before)
    want = mixing.targets([before[s] for s in names], [mixing.WEIGHTS[k % 3] for k in range(len(names))])
    for s, t in zip(names, want):
        assert abs(after.get(s, 0) - t) <= 1


def test_bpe_stage(stages):
    c = bpe.codec(public_tokenizers.path(corpus_pipeline.VOCABULARY), public_tokenizers.PATTERN)
    texts = sorted(r["text"] for r in stages[4].collect())
    rows = stages[5].collect()
    assert sorted(c.decode(r["ids"]).decode() for r in rows) == texts and all(r["n_tokens"] == len(r["ids"]) for r in rows)


def test_bpe_stage_decodes(stages):
    told = sorted((r["doc_id"], r["decoded_sha256"]) for r in stages[5].collect())
    assert told == sorted((r["doc_id"], hashlib.sha256(r["text"].encode()).hexdigest()) for r in stages[4].collect())


def test_run(spark, stages):
    key = lambda df: sorted((r["doc_id"], r["n_tokens"]) for r in df.collect())
    assert key(corpus_pipeline.run(spark, SMALL)) == key(stages[5])


def test_pipeline_on_awkward_and_empty_tables(spark, tmp_path):
    """Nulls, repeated rows, clashing columns; then no rows at all."""
    long = " ".join(f"w{i}" for i in range(60))
    rows = [(1, long, None, "a", None, 1), (1, long, None, "a", None, 1), (2, None, "en", None, 3, 2), (None, long + " more words here", "en", "b", 1, 3), (4, "", None, None, None, None), (5, long.upper() + " tail", "de", "a", 9, 5)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint, `__id` int")
    for name, table in (("some", df), ("none", df.limit(0))):
        table.write.parquet(f"{tmp_path}/{name}/documents.parquet")
        out = corpus_pipeline.run(spark, f"{tmp_path}/{name}").collect()
        assert (len(out) > 0) == (name == "some") and all(r["n_tokens"] == len(r["ids"]) for r in out)
