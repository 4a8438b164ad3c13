"""Terms beside entities of one or two documents."""

from conflate.llm import pii


def test_rare_entities_disclose_their_terms(spark, docs_of):
    rows = [(1, "write to quillon at jane@corp.example now"), (2, "ask for brennus " + "1 " * 600 + "+1 202 555 0147 today")]
    rows += [(100 + i, "write to ask for now today at word") for i in range(60)]
    got = {r.doc_id: r for r in pii.find(docs_of(rows), texts=True).collect()}
    assert "quillon" not in got[1].clean and "write" in got[1].clean and "term:9:16" in got[1].spans
    assert "brennus" not in got[2].clean and "ask" in got[2].clean
    assert got[100].spans == ""
