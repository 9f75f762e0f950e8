"""The stages over the smallest tables, each against a plain version of what it decides."""

from collections import Counter

import public_tokenizers
import pytest
from tokenizers import Tokenizer

import corpus_pipeline as cp
from rarespan.llm import pii, toxicity
from tests.llm.test_simhash import brute

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    folder = tmp_path_factory.mktemp("stages")
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    out = [docs]
    for name, stage in cp.STAGES:
        stage(spark, out[-1], SF).write.parquet(f"{folder}/{name}")
        out.append(spark.read.parquet(f"{folder}/{name}"))
    return out


def test_columns_and_order(stages):
    assert [n for n, _ in cp.STAGES] == ["toxicity", "near_duplicates", "personal_data", "mixture", "packing"]
    for df in stages[1:5]:
        assert df.dtypes == stages[0].dtypes


def test_toxicity_keeps_what_scores_low(spark, stages):
    model = toxicity.train(stages[0], spark.read.parquet(f"{SF}/labels.parquet"))
    low = {r.doc_id for r in toxicity.score_documents(stages[0], model).collect() if r.toxicity < 0.5}
    assert {r.doc_id for r in stages[1].collect()} == low and len(low) > 0.7 * stages[0].count()


def test_one_of_each_group_stays(stages):
    rows = [(r.doc_id, r.text) for r in stages[1].collect()]
    kept = {r.doc_id for r in stages[2].collect()}
    assert kept <= {c for _, _, c in brute(rows)} and stages[2].count() == len(kept)
    words = {i: t.lower().split() for i, t in rows}
    grams = {i: {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} for i, w in words.items()}
    like = lambda a, b: len(grams[a] & grams[b]) / len(grams[a] | grams[b])
    assert not any(like(a, b) >= 0.85 for a in kept for b in kept if a < b)
    assert all(max(like(i, j) for j in words if j != i) >= 0.5 for i in words if i not in kept)


def test_personal_data_is_masked(stages):
    before = {r.doc_id: r for r in stages[2].collect()}
    after = stages[3].collect()
    assert len(after) == len(before)
    changed = 0
    for r in after:
        assert r.n_chars == len(r.text) and r.lang == before[r.doc_id].lang
        assert not any(list(pii._base(k, r.text)) for k in pii.KINDS[:4])
        changed += r.text != before[r.doc_id].text
    assert changed > 0


def test_mixture_repeats_whole_documents(stages):
    texts = {r.doc_id: r.text for r in stages[3].collect()}
    times = Counter()
    for r in stages[4].collect():
        assert r.text == texts[r.doc_id]
        times[r.doc_id] += 1
    assert max(times.values()) <= 2
    size = {i: len(t.split()) for i, t in texts.items()}
    assert abs(sum(size[i] * k for i, k in times.items()) / (1.5 * sum(size.values())) - 1) < 0.1


def test_packing_tiles_every_text(stages):
    tokenizer = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    want = Counter()
    for r in stages[4].collect():
        want[r.doc_id] += 1 + len(tokenizer.encode(r.text, add_special_tokens=False).ids)
    got = Counter()
    for r in stages[5].collect():
        got[r.doc_id] += r.length
    assert got == want


def test_empty_documents(spark, stages):
    none = stages[0].limit(0)
    for _, stage in cp.STAGES:
        assert stage(spark, none, SF).collect() == []
