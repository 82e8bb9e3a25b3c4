"""The corpus pipeline stage by stage."""

import hashlib
import re

import pytest

pytest.importorskip("rulefeat.llm")
corpus_pipeline = pytest.importorskip("corpus_pipeline")

from tests.llm.test_operators import SCHEMA, plain, rows  # noqa: E402


def test_stages_on_the_small_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, seen = docs.columns, {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = {(r["doc_id"], r["text"]) for r in docs.collect()}
        docs = spark.createDataFrame(stage(spark, docs, sf).collect(), docs.schema)
        assert docs.columns == columns
        after = [(r["doc_id"], r["text"]) for r in docs.collect()]
        assert set(after) <= before
        seen[name] = (before, after)
    before, after = seen["exact_dedup"]
    assert sorted(plain(t) for _, t in after) == sorted({plain(t) for _, t in before})
    before, after = seen["simhash_near_dedup"]
    ids, texts = zip(*before)
    assert sorted(i for i, _ in after) == sorted({min(ids[k] for k, g in enumerate(groups) if g == own) for groups in [slow_groups(texts)] for own in groups})
    before, after = seen["source_mix"]
    assert max(after.count(x) for x in set(after)) <= 3
    final = corpus_pipeline.STAGES[-1][1](spark, docs, sf).collect()
    assert len(final) == len(after) and set(columns) < set(final[0].asDict())
    import public_tokenizers
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    for r in final:
        ids = lib.encode(r["text"], add_special_tokens=False).ids
        assert list(r["token_ids"]) == ids and r["n_tokens"] == len(ids)
        assert r["decoded_sha256"] == hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest()


def test_stages_on_odd_rows(spark, sf, tmp_path):
    schema = SCHEMA.replace("key string", "`Doc_ID2` string")
    for data in (rows(), []):
        docs = spark.createDataFrame(data, schema)
        for _, stage in corpus_pipeline.STAGES[:-1]:
            out = stage(spark, docs, sf)
            assert out.columns == docs.columns
            docs = spark.createDataFrame(out.collect(), docs.schema)
        assert corpus_pipeline.STAGES[-1][1](spark, docs, sf).count() == docs.count()


def slow_groups(texts, width=5):
    """Group numbers by brute force: chains of pairs with a similarity of 0.8 or more."""
    sets = []
    for t in texts:
        w = [x for x in re.split(r"[\x20\x09-\x0D]+", "".join(c.lower() if c.isascii() else c for c in t or "")) if x]
        sets.append({tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else {()})
    group = list(range(len(texts)))
    for i, a in enumerate(sets):
        for j in range(i):
            if group[i] != group[j] and 5 * len(a & sets[j]) >= 4 * len(a | sets[j]):
                old, new = max(group[i], group[j]), min(group[i], group[j])
                group = [new if g == old else g for g in group]
    return group


@pytest.mark.parametrize("group", [16, 2])
def test_edited_copies_leave_one_as_by_brute_force(spark, monkeypatch, group):
    import random

    from rulefeat.llm import near_join

    monkeypatch.setattr(near_join, "GROUP", group)

    draw, texts = random.Random(8), []
    for size in [3, 5, 8, 30, 60, 100, 200, 400] * 3:
        base = [f"w{draw.randrange(3000)}" for _ in range(size)] + ["a", "line", "that", "many", "texts", "have", "at", "their", "end"]
        texts.append(" ".join(base))
        for edits in (0, 1, 2, 4, 8):
            copy = list(base)
            for _ in range(edits):
                copy[draw.randrange(len(copy))] = f"e{draw.randrange(10**6)}"
            texts.append(("  " if edits else " ").join(copy))
    texts += [None, "", " \n", "One two", "one TWO"]
    want = sorted(set(slow_groups(texts)))
    assert 40 < len(want) < len(texts) - 40
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    stage = dict(corpus_pipeline.STAGES)["simhash_near_dedup"]
    assert sorted(r["doc_id"] for r in stage(spark, docs, "").collect()) == want


def test_stage_names():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "exact_dedup", "simhash_near_dedup", "source_mix", "bpe_encode"]
    assert corpus_pipeline.ORACLE_SQL is None and re and hashlib
