"""The corpus pipeline against its stages done one by one on the small tables."""

import pytest

import corpus_pipeline

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def steps(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    out = [docs.toPandas()]
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF).cache()
        out.append(docs.toPandas())
    return out


def test_stages_filter_and_keep_columns(steps):
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["toxicity", "exact_dedup", "near_dedup", "decontamination", "byte_bpe"]
    for before, after in zip(steps, steps[1:-1]):
        assert list(after.columns) == list(steps[0].columns)
        assert set(after.doc_id) <= set(before.doc_id) and after.doc_id.is_unique
    assert sorted(steps[-1].doc_id) == sorted(steps[-2].doc_id) and steps[-1].restored.all()


def test_exact_and_near_stages_equal_brute_force(steps):
    from tests.llm.test_documents import SPACE, brute_components

    seen = {}
    for i, t in sorted(zip(steps[1].doc_id, steps[1].text)):
        seen.setdefault(SPACE.sub(" ", t or ""), i)
    assert sorted(steps[2].doc_id) == sorted(seen.values())
    found = brute_components(list(zip(steps[2].doc_id, steps[2].text)), 5, 80)
    assert sorted(steps[3].doc_id) == sorted(i for i, (_, root) in found.items() if i == root)


def test_run_equals_the_steps(spark, steps):
    got = corpus_pipeline.run(spark, SF).toPandas()
    assert sorted(got.doc_id) == sorted(steps[-1].doc_id)
    assert dict(zip(got.doc_id, got.n_tokens)) == dict(zip(steps[-1].doc_id, steps[-1].n_tokens))


def slow_score(text, lexicon, model):
    """The grammar rule by rule over plainly split clauses."""
    import math
    import re

    from motifmill.llm import toxicity
    from tests.llm.test_documents import plain_clause

    symbol = {"threat": "t", "target": "g", "negation": "n", "report": "r"}
    scores = []
    for clause in re.split(r"[.!?;:\n]", (text or "").lower()):
        own, hit = [], False
        for m in re.finditer(r"[^\W\d_]+(?:'[^\W\d_]+)?", clause):
            word, free = m[0], not (m.start() and (clause[m.start() - 1].isalpha() or clause[m.start() - 1] == "'"))
            letters = re.match(r"[^\W\d_]+", word)[0]
            fits = [w for e, w in lexicon.items() if free and (letters.startswith(e[1:]) or word.startswith(e[1:]) if e[0] == "*" else letters == e[1:] or word == e[1:])]
            kind = symbol.get(toxicity._CLASS_OF.get(word), "o")
            own.append(("i", max(fits)) if fits else (kind, 0.0))
            hit |= bool(fits) or kind == "t"
        if hit and (s := plain_clause(own)) > 0:
            scores.append(s)
    x = [1.0, math.log1p(sum(scores)), max(scores), math.log1p(len(scores))] if scores else [0.0] * 4
    return 1 / (1 + math.exp(-(model[0] + sum(a * b for a, b in zip(model[1:], x)))))


def test_toxicity_stage_equals_a_slow_version(spark, steps):
    from motifmill.llm import toxicity

    lexicon, model = toxicity.learn(spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet"))
    slow = {i: slow_score(t, lexicon, model) for i, t in zip(steps[0].doc_id, steps[0].text)}
    assert set(steps[1].doc_id) == {i for i, s in slow.items() if s < 0.5}
    got = toxicity.score(spark.read.parquet(f"{SF}/documents.parquet"), lexicon, model).toPandas()
    assert max(abs(s - slow[i]) for i, s in zip(got.doc_id, got.score)) < 1e-9


def test_decontamination_stage_equals_brute_force(spark, steps):
    """Every window of every document against every item, by the exact distance."""
    import re

    import numpy as np

    from motifmill.llm import decontaminate

    items = [re.sub(r"[\x00-/:-@\[-`{-\x7f]", " ", (t or "").lower() if (t or "").isascii() else "".join(c.lower() if c.isascii() else c for c in t or "")).split() for t in spark.read.parquet(f"{SF}/benchmark.parquet").toPandas().text]
    dirty = set()
    for i, t in zip(steps[3].doc_id, steps[3].text):
        own = re.sub(r"[\x00-/:-@\[-`{-\x7f]", " ", "".join(c.lower() if c.isascii() else c for c in t or "")).split()
        ids = {w: k for k, w in enumerate(dict.fromkeys(own))}
        text = np.array([ids[w] for w in own], np.uint64)
        for item in items:
            k = decontaminate.tolerated(len(item))
            if item and sum(w in ids for w in item) >= len(item) - k:
                row = np.array([[ids.get(w, 10**9) for w in item]], np.uint64)
                if len(text) and decontaminate.substring_distances(row, text[None, :])[0] <= k:
                    dirty.add(i)
                    break
    assert set(steps[4].doc_id) == set(steps[3].doc_id) - dirty


def test_stages_take_odd_rows(spark):
    """Nulls in any column, empty and long texts, repeated rows, extra columns with clashing names, no rows."""
    rows = [
        (1, "some plain words here", "en", "s", 21, "a"), (1, "some plain words here", "en", "s", 21, "a"), (None, "some plain words here", None, None, None, None),
        (2, None, None, None, None, None), (3, "", "en", None, 0, "b"), (4, "word " * 60_000, None, "s", None, "c"), (5, " \n\t", "en", "s", 3, None), (None, None, None, None, None, None),
    ]
    schema = "doc_id long, text string, lang string, source string, n_chars long, node string"
    for given in (rows, []):
        docs = spark.createDataFrame(given, schema)
        for name, stage in corpus_pipeline.STAGES[:-1]:
            docs = spark.createDataFrame(stage(spark, docs, SF).collect(), schema)
            assert docs.columns == [c.split()[0] for c in schema.split(", ")]
        last = corpus_pipeline.STAGES[-1][1](spark, docs, SF).collect()
        assert len(last) == docs.count() and all(r.restored for r in last)
        # null and empty texts are one group of equal texts, whose least id stays; rows without id stay
        assert sorted(r.doc_id or 0 for r in last) == ([0, 0, 1, 1, 2, 4, 5] if given else []), name
