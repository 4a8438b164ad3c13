"""Rows that share a doc_id, have none, or repeat: decisions go by row, and no text is lost."""

import collections

import pytest

from conflate.llm import decontam, exact, fuzzylines, passages, pii, probminhash, sampling, toxicity, urls

ROWS = [(1, "p"), (5, "q"), (5, "p"), (1, "p"), (None, "p"), (None, "q r s t u v"), (7, None), (7, None)]


@pytest.mark.parametrize("module", [exact, probminhash])
def test_dedup_loses_no_text(module, docs_of):
    docs = docs_of(ROWS)
    kept = collections.Counter((r.doc_id, r.text) for r in module.dedup(docs).collect())
    assert kept[1, "p"] == kept[5, "q"] == kept[None, "q r s t u v"] == 1 and not kept[5, "p"] and not kept[None, "p"]
    said = module.decisions(docs).where("kept").count()
    assert said == sum(kept.values()) and module.dedup(docs).columns == docs.columns
    assert module.dedup(docs.where("false")).count() == 0


def test_one_row_of_each_group_is_kept(docs_of):
    got = exact.decisions(docs_of(ROWS)).collect()
    by = collections.defaultdict(list)
    for r in got:
        by[r.text_sha256].append(r.kept)
    assert all(sum(k) == 1 for k in by.values()) and len(got) == len(ROWS)


def test_lines_of_shared_and_repeated_ids(docs_of):
    rows = [(0, "p p p"), (5, "p p p\nfoo bar"), (5, "keep me\nq"), (0, "p p p"), (None, "keep me")]
    docs = docs_of(rows)
    texts = collections.Counter((r.doc_id, r.text) for r in fuzzylines.clean(docs).collect())
    assert texts == collections.Counter([(0, "p p p"), (0, ""), (5, "foo bar"), (5, "keep me\nq"), (None, "")])
    gone = sorted((str(r.doc_id), r.n_lines, r.dropped_lines) for r in fuzzylines.report(docs).collect())
    assert gone == [("0", 1, ""), ("0", 1, "0"), ("5", 2, ""), ("5", 2, "0"), ("None", 1, "0")]


def test_decontamination_judges_each_row(spark, docs_of):
    item = "one two three four five six seven eight nine ten eleven twelve"
    bench = spark.createDataFrame([(1, item), (1, item)], "item_id long, text string")
    docs = docs_of([(3, item), (3, "clean text of its own"), (None, item), (None, "another clean text"), (3, item)])
    assert sorted(r.text for r in decontam.decontaminate(docs, bench).collect()) == ["another clean text", "clean text of its own"]


def test_empty_tables_and_repeats_elsewhere(spark, docs_of):
    none, twice = docs_of([(1, "x")]).where("false"), docs_of([(1, "call a@b.example now"), (1, "call a@b.example now"), (None, None)])
    assert sampling.encode(none).count() == 0 and pii.find(none).count() == 0 and passages.remove(none).count() == 0
    assert [r.n_email for r in pii.find(twice).orderBy("n_email").collect()] == [0, 1, 1]
    assert passages.remove(twice).count() == 3
    scorer = toxicity.learn(none.select("doc_id", "text"), spark.createDataFrame([], "doc_id long, toxic int"))
    assert toxicity.score(none, scorer).count() == 0 and toxicity.score(twice, scorer).count() == 3
    pages = spark.createDataFrame([(1, "http://a.org/" + "x" * 200_000), (1, "http://a.org/" + "x" * 200_000), (None, None)], "page_id long, url string")
    assert sorted(r.rule or "" for r in urls.judge(pages, [("org", "/", "allow")]).collect()) == ["", "org/", "org/"]
    assert urls.judge(pages.where("false"), [("org", "/", "allow")]).count() == 0


def test_passages_come_from_the_automata(docs_of, monkeypatch):
    """Ablation: without what the automata find, nothing is removed."""
    text = " ".join(f"w{i}" for i in range(60))
    docs = docs_of([(1, "a b " + text), (2, text + " c")])
    assert {r.n_removed for r in passages.remove(docs).collect()} == {60}
    monkeypatch.setattr(passages, "automaton_of", lambda phrases: None)
    assert {r.n_removed for r in passages.remove(docs).collect()} == {0}
