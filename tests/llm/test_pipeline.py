"""The stages of the corpus pipeline on a small table, each held against a plain version."""

import os
import random
import re

import pytest

import corpus_pipeline
from linkwhy.llm import codec, common, langid
from linkwhy.llm.bpe import default_vocabulary

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def outputs(spark):
    """The input of the first stage and the outputs of all, as lists of rows."""
    if not os.path.isdir(SF):
        pytest.skip("the given tables are not here")
    docs = common.table(spark, SF, "documents")
    found = [docs]
    for _, stage in corpus_pipeline.STAGES:
        found.append(common.settle_table(stage(spark, found[-1], SF)))
    return found


def test_every_stage_but_the_last_keeps_the_columns(outputs):
    assert all(df.columns == outputs[0].columns for df in outputs[:-1])
    sizes = [df.count() for df in outputs]
    assert sizes == sorted(sizes, reverse=True) and sizes[-1] > sizes[0] // 3


def test_language_stage_keeps_what_the_network_accepts(outputs):
    docs, kept = outputs[0], outputs[1]
    model = langid.fit(docs, common.crc_mod("doc_id", 4) != 2)
    want = {r.doc_id for r in langid.predict(docs, model).collect() if r.lang_pred != "und" and r.score >= 0.4}
    assert {r.doc_id for r in kept.collect()} == want
    before = {r.doc_id: r for r in docs.collect()}
    assert all(before[r.doc_id] == r for r in kept.collect())


def near(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def kept_by_brute_force(rows):
    sets, top = {i: near(t) for i, t in rows}, {i: i for i, _ in rows}

    def find(x):
        while top[x] != x:
            x = top[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                top[max(find(a), find(b))] = min(find(a), find(b))
    return sorted({find(i) for i in sets})


def test_near_dedup_stage_takes_five_words_and_a_similarity_of_four_fifths(spark, outputs):
    rng = random.Random(3)
    rows = []
    for g in range(12):  # copies with one to five words changed, and chains of them
        own = [f"w{rng.randrange(900)}" for _ in range(rng.randint(4, 120))]
        for _ in range(12):
            rows.append((len(rows), " ".join(own)))
            own = list(own) if g % 2 else own
            for _ in range(rng.randint(0, 3)):
                own[rng.randrange(len(own))] = f"w{rng.randrange(900)}"
    rows += [(900, None), (901, ""), (902, " \n"), (903, rows[0][1].upper())]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert sorted(r.doc_id for r in corpus_pipeline.near_dedup(spark, df, SF).collect()) == kept_by_brute_force(rows)
    given = [(r.doc_id, r.text) for r in outputs[2].collect()]
    assert sorted(r.doc_id for r in outputs[3].collect()) == kept_by_brute_force(given)
    assert corpus_pipeline.near_dedup(spark, df.filter("false"), SF).count() == 0


def test_last_stage_gives_the_identifiers_of_the_library(outputs):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(default_vocabulary())
    text = {r.doc_id: r.text or "" for r in outputs[4].collect()}
    got = outputs[5].collect()
    assert {r.doc_id for r in got} == set(text)
    for r in got:
        ids = lib.encode(text[r.doc_id], add_special_tokens=False).ids
        assert list(r.ids) == ids and r.n_tokens == len(ids)
        assert r.round_trip == (lib.decode(ids, skip_special_tokens=False) == text[r.doc_id])


def test_verified_encoding_compares_whole_texts(spark):
    rows = [(1, None), (2, ""), (3, "a<|endoftext|> b é日本"), (4, "x y " * 70_000)]
    got = codec.encode_documents(spark.createDataFrame(rows, "doc_id long, text string"), verify=True).collect()
    assert len(got) == 4 and all(r.round_trip for r in got)
