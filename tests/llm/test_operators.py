import collections
import hashlib
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from conflate.llm import decontam, exact, fuzzylines, langid, passages, pii, probminhash, queries, sampling, toxicity, urls
from conflate.llm.textkit import ALNUM, Words
from tests.helpers import plain

random.seed(4)
VOCAB = ["".join(random.choice("abcdefghijklmnop") for _ in range(random.randint(3, 8))) for _ in range(900)]


def prose(n, seed):
    r = random.Random(seed)
    return " ".join(r.choice(VOCAB) for _ in range(n))


def collect(df):
    return [r.asDict() for r in df.collect()]


# ---- words -----------------------------------------------------------------------------------------------------------

def test_words_and_windows():
    texts = ["a bb  ccc\ta bb ccc", "", None, "  é x ", "a bb ccc"]
    w = Words(pa.array(texts))
    assert w.counts().tolist() == [6, 0, 0, 2, 3]
    at, h = w.windows(3)
    by = {}
    for i, x in zip(at.tolist(), h.tolist()):
        by.setdefault(x, []).append(i)
    assert sorted(map(tuple, by.values()), key=len)[-1] == (0, 3, 8)


# ---- language --------------------------------------------------------------------------------------------------------

def test_language_profiles(spark, docs_of, odd):
    one, two = "der die und schule macht heute nicht viel spass aber morgen", "the and of school makes today not much fun but later"
    rows = [(i, " ".join(random.Random(i).sample((one if i % 2 else two).split(), 8)), "de" if i % 2 else "en") for i in range(60)]
    train = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    p = langid.learn(train)
    assert p.languages == ["de", "en"]
    got = langid.predict(train, p, ["doc_id", "lang"]).collect()
    assert sum(r.lang == r.lang_pred for r in got) >= 58 and all(0 <= r.score <= 1 for r in got)
    strange = {(r.doc_id, r.lang_pred) for r in langid.predict(docs_of(odd), p).collect()}
    assert {(1, "und"), (2, "und"), (3, "und"), (5, "und")} <= strange and (7, "und") not in strange
    nothing = langid.learn(train.where("false"))
    assert {r.lang_pred for r in langid.predict(train, nothing).collect()} == {"und"}
    assert langid.predict(train.where("false"), p).count() == 0


def test_language_ngrams_by_hand():
    k, c = langid.ngrams("Ab ab")
    names = {}
    for key, n in zip(k.tolist(), c.tolist()):
        s = ""
        while key:
            s, key = s + ("_" if key & 0xFFFF == 1 else chr(key & 0xFFFF)), key >> 16
        names[s] = n
    assert names == {"a": 2, "b": 2, "_a": 2, "ab": 2, "b_": 2, "_ab": 2, "ab_": 2, "_ab_": 2}


def test_language_accuracy_on_held_out_rows(spark, sf_dir):
    got = queries.op1_language_profiles(spark, sf_dir).join(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert sum(r.lang == r.lang_pred for r in got) / len(got) > 0.93


# ---- near dedup ------------------------------------------------------------------------------------------------------

def bag(text):
    w = re.findall(r"(?:[a-z0-9]|[^\x00-\x7f])+", (text or "").lower())
    return collections.Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4)) or (collections.Counter([tuple(w)]) if w else collections.Counter())


def slow_similarity(a, b):
    keys = set(a) | set(b)
    return sum(1 / sum(max(a.get(y, 0) / a[x], b.get(y, 0) / b[x]) for y in keys) for x in set(a) & set(b))


def test_similarity_is_exact_and_estimated():
    x, y = prose(80, 1) + " " + prose(20, 2) * 2, prose(80, 1) + " " + prose(20, 3)
    w = Words(pa.array([x, y]), ALNUM, True)
    d, e, n = probminhash.elements(w, 5)
    a = d == 0
    exact_j = probminhash.similarity(e[a], n[a], e[~a], n[~a])
    assert exact_j == pytest.approx(slow_similarity(bag(x), bag(y)))
    s = probminhash.signatures(d, e, n, 2, 4000)
    assert abs((s[0] == s[1]).mean() - exact_j) < 0.04


def near_rows():
    base = [prose(120, i) for i in range(12)]
    rows = list(enumerate(base))
    for i, b in enumerate(base[:8]):
        w = b.split()
        w[60] = "changed"
        rows += [(100 + i, " ".join(w)), (200 + i, b), (300 + i, b.upper() + "!")]
    hot = prose(200, 77).split()
    for i in range(90):  # one large family of copies, each with a word of its own
        w = list(hot)
        w[i * 2] = f"own{i}"
        rows.append((1000 + i, " ".join(w)))
    return rows


def roots_of(rows):
    bags = [bag(t) for _, t in rows]
    parent = list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if bags[i] and bags[j] and (bags[i] == bags[j] or slow_similarity(bags[i], bags[j]) >= 0.8):
                parent[max(find(i), find(j))] = min(find(i), find(j))
    groups = collections.defaultdict(list)
    for i in range(len(rows)):
        groups[find(i)].append(rows[i][0])
    return {x: min(g) for g in groups.values() for x in g}


def test_near_dedup_equals_brute_force(spark, docs_of):
    rows = near_rows()
    got = {r.doc_id: r.class_id for r in probminhash.classes_of(docs_of(rows)).collect()}
    assert got == roots_of(rows)


def test_near_dedup_odd_rows(spark, docs_of, odd):
    got = collect(probminhash.classes_of(docs_of(odd)))
    assert len(got) == len(odd)
    assert all(r["kept"] and r["class_size"] == 1 for r in got if r["doc_id"] in (1, 2, 3, 5, 6, 7)) and sum(r["kept"] for r in got if r["doc_id"] in (4, None)) == 1
    assert {r["class_id"] for r in got if r["doc_id"] in (4, None)} == {4}
    kept = probminhash.dedup(docs_of(odd))
    assert kept.columns == docs_of(odd).columns and kept.where("doc_id = 6").count() == 1
    assert probminhash.classes_of(docs_of(odd).where("false")).count() == 0


# ---- personal data ---------------------------------------------------------------------------------------------------

def slow_base(text):
    out = [(m.start(), 0, m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    out += [(m.start(), 1, m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(x) <= 255 for x in m.group().split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        d = [int(c) for c in m.group() if c.isdigit()]
        if 14 <= len(d) <= 19 and sum(x if i % 2 == 0 else (2 * x if x < 5 else 2 * x - 9) for i, x in enumerate(reversed(d))) % 10 == 0:
            out.append((m.start(), 2, m.end()))
    out += [(m.start(), 3, m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 10 <= sum(c.isdigit() for c in m.group()) <= 15]
    return sorted(out)


def test_base_spans_equal_plain_patterns():
    r = random.Random(2)
    alphabet = ["a", "b.c", "@", "@@", ".", "-", "+", "1", "23", "255", "256", " ", "(", ")", "4111111111111111", "x@y.z", "é", "_", "%", "+1 (456) 555-2186", "1.2.3.4", "\n"]
    for _ in range(4000):
        t = "".join(r.choice(alphabet) for _ in range(r.randint(0, 25)))
        assert pii.base_spans(t) == slow_base(t), t


def test_long_runs_are_quick():
    for t in ("1" * 60_000, "a" * 100_000 + "@", "1." * 30_000, "+" * 50_000, "@" * 50_000):
        pii.base_spans(t)


def test_disclosing_terms(spark, docs_of):
    rows = [(i, f"call secretword about jane@corp.example now common word") for i in range(5)] + [(100 + i, f"common word now call {prose(5, i)}") for i in range(60)]
    rows += [(300, None), (301, "")]
    got = {r["doc_id"]: r for r in collect(pii.find(docs_of(rows), texts=True))}
    assert got[0]["n_email"] == 1 and "term:" in got[0]["spans"] and "secretword" not in got[0]["clean"] and "common" in got[0]["clean"] and "[email]" in got[0]["clean"]
    assert got[100]["spans"] == "" and got[300]["spans"] == "" and got[300]["base_sha256"] == hashlib.sha256(b"").hexdigest()
    assert pii.find(docs_of([]).where("false")).count() == 0


def test_pii_query_equals_brute_force(spark, sf_dir):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()}
    for r in queries.op3_disclosure_pii(spark, sf_dir).collect():
        base = slow_base(docs[r.doc_id] or "")
        named = ",".join(f"{pii.KINDS[k]}:{s}:{z}" for s, k, z in base)
        assert r.base_sha256 == hashlib.sha256(named.encode()).hexdigest() and r.n_email + r.n_ip + r.n_card + r.n_phone == len(base)
        assert set(named.split(",")) <= {"", *r.spans.split(",")}


# ---- toxicity --------------------------------------------------------------------------------------------------------

def test_weak_supervision(spark, docs_of):
    r = random.Random(1)
    rows, marks = [], []
    for i in range(400):
        words = prose(40, i).split()
        if i % 8 == 0:
            words[3:3] = ["zorg" + r.choice(["a", "ik", "un"]), "vile" if i % 16 else "nasty"]
        rows.append((i, " ".join(words)))
        marks.append((i, int(i % 8 == 0)))
    docs = docs_of(rows + [(900, None), (901, "")])
    scorer = toxicity.learn(docs.where("doc_id < 300"), spark.createDataFrame(marks, "doc_id long, toxic int"))
    got = {x.doc_id: x.score for x in toxicity.score(docs, scorer).collect()}
    held = [(got[i] >= toxicity.CUT) == (i % 8 == 0) for i in range(300, 400)]
    assert sum(held) >= 97 and got[900] == got[901] < toxicity.CUT and all(0 <= s <= 1 for s in got.values())
    none = toxicity.learn(docs, spark.createDataFrame([], "doc_id long, toxic int"))
    assert all(x.score < 0.01 for x in toxicity.score(docs, none).collect())


def test_label_model_shares_correlated_votes():
    rng = np.random.default_rng(0)
    y = rng.random(600) < 0.3
    one = np.where(rng.random(600) < np.where(y, 0.6, 0.05), 1, -1)
    other = np.where(rng.random(600) < np.where(y, 0.6, 0.05), 1, -1)
    post, p1, p0, share = toxicity.label_model(np.stack([one, one, one, other], 1).astype(np.int8), np.where(rng.random(600) < 0.5, y, -1).astype(int))
    assert share[0] < 0.5 < share[3] and p1[0, 1] > p1[0, 0] and post[y].mean() > post[~y].mean() + 0.4


# ---- lines -----------------------------------------------------------------------------------------------------------

def test_fuzzy_lines(spark, docs_of, odd):
    line = prose(40, 5)
    near = line[:-1] + "z"
    rows = [(1, f"{line}\n\n{prose(30, 6)}"), (2, f"{prose(30, 7)}\n{line.upper()}."), (3, near), (4, f"{line}\n{line}\n---"), (5, prose(30, 8)), (6, "x\nx"), (7, prose(40, 90))]
    got = {r["doc_id"]: r["dropped_lines"] for r in collect(fuzzylines.report(docs_of(rows)))}
    assert (got[1], got[2], got[4], got[5], got[6], got[7]) == ("", "1", "0,1", "", "1", "")
    clean = {r["doc_id"]: r["text"] for r in collect(fuzzylines.clean(docs_of(rows)))}
    assert clean[4] == "---" and clean[5] == rows[4][1]
    strange = {r["doc_id"]: r for r in collect(fuzzylines.report(docs_of(odd)))}
    assert strange[1]["n_dropped"] == strange[2]["n_dropped"] == strange[6]["n_dropped"] == 0
    alike = sorted(r["n_dropped"] for r in collect(fuzzylines.report(docs_of(odd))) if r["doc_id"] in (4, None))
    assert alike == [0, 1, 1]
    assert fuzzylines.report(docs_of(odd).where("false")).count() == 0


def test_line_blocks(spark, docs_of):
    a, b, c = 0b1100, 0b1010, 0b1001
    got = spark.range(1).select(fuzzylines._majority([F.lit(x) for x in (a, b, c)]).alias("x"), fuzzylines._majority([F.lit(x) for x in (a, b, c, 0b0111)]).alias("y")).collect()[0]
    assert (got.x, got.y) == (0b1000, 0b1110 & 0b1100 | 0b0010 & 0b0000 | 0b1000)
    line = prose(40, 5)
    words = line.split()
    words[7] = "other"
    rows = {r.doc_id: set(r.blocks) for r in fuzzylines.fingerprints(docs_of([(1, line), (2, " ".join(words)), (3, prose(40, 6)), (4, "short line"), (5, "---")])).collect()}
    assert rows[1] & rows[2] and not rows[1] & rows[3] and len(rows[1]) == fuzzylines.BLOCKS and len(rows[4]) == fuzzylines.GRAM_BLOCKS and not rows[5]
    plan = fuzzylines.report(docs_of([(1, "a")]))._jdf.queryExecution().toString()
    assert "Python" not in plan and "Pandas" not in plan and "Arrow" not in plan


# ---- passages --------------------------------------------------------------------------------------------------------

def slow_removal(rows, size):
    words = [re.findall("[^\x20\x09-\x0D]+", t or "") for _, t in rows]
    n = collections.Counter(tuple(w[i : i + size]) for w in words for i in range(len(w) - size + 1))
    out = []
    for (d, _), w in zip(rows, words):
        gone = [False] * len(w)
        for i in range(len(w) - size + 1):
            if n[tuple(w[i : i + size])] > 1:
                gone[i : i + size] = [True] * size
        out.append((d, len(w), sum(gone), " ".join(x for x, g in zip(w, gone) if not g)))
    return sorted(out, key=str)


def test_passages_equal_brute_force(spark, docs_of, odd):
    shared = prose(60, 11)
    rows = [(i, f"{prose(20 + i, i)} {shared if i % 3 else shared[: len(shared) // 2]} {prose(15, 50 + i)}") for i in range(14)]
    rows += [(20, "la " * 90), (21, f"{shared} x {shared}"), (22, prose(34, 9)), (23, prose(34, 9)), (24, prose(35, 10)), (25, prose(35, 10)), *odd]
    got = sorted(map(tuple, passages.remove(docs_of(rows)).collect()), key=str)
    assert got == slow_removal(rows, passages.SIZE)
    assert passages.remove(docs_of(rows).where("false")).count() == 0


def test_passage_query_equals_brute_force(spark, sf_dir):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()]
    got = sorted(((r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in queries.op6_phrase_automata(spark, sf_dir).collect()), key=str)
    assert got == [(d, n, k, hashlib.sha256(t.encode()).hexdigest()) for d, n, k, t in slow_removal(rows, 35)]


# ---- benchmark -------------------------------------------------------------------------------------------------------

def slow_matches(rows, items):
    out = {}
    for i, t in items:
        n, b = len(re.findall(r"(?:[a-z0-9]|[^\x00-\x7f])+", (t or "").lower())), bag(t)
        for d, text in rows:
            w = re.findall(r"(?:[a-z0-9]|[^\x00-\x7f])+", (text or "").lower())
            if n < 5:
                hits = [1.0 for s in range(len(w) - n + 1) if n and collections.Counter([tuple(w[s : s + n])]) == b]
            else:
                sh = [tuple(w[s : s + 5]) for s in range(len(w) - 4)]
                span = min(n - 4, len(sh))
                hits = []
                for s in range(len(sh) - span + 1) if span else ():
                    c = collections.Counter(sh[s : s + span])
                    m = sum((c & b).values())
                    hits.append(m / (span + sum(b.values()) - m))
            if hits and max(hits) >= 0.8:
                out[d, i] = max(hits)
    return out


def test_decontamination_equals_brute_force(spark, docs_of, odd):
    items = [(i, prose(18 + 3 * i, 400 + i)) for i in range(6)] + [(7, "alpha beta gamma"), (8, None), (9, ""), (10, prose(18, 400))]
    rows = [(i, f"{prose(30, i)} {items[i % 6][1].upper()}. {prose(10, 60 + i)}") for i in range(8)]
    w = items[5][1].split()
    rows += [(20, prose(20, 1) + " " + " ".join([*w[:3], "odd", *w[3:]])), (21, " ".join(w[:-2])), (22, " ".join(w[: len(w) // 2])), (23, "so alpha, beta gamma it is"), (24, prose(60, 99)), *odd]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id): r.similarity for r in decontam.matches(docs_of(rows), bench).collect()}
    want = slow_matches(rows, items)
    assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k]) for k in want)
    kept = {r.doc_id for r in decontam.decontaminate(docs_of(rows), bench).collect()}
    assert {22, 24} <= kept and 0 not in kept
    assert decontam.matches(docs_of(rows), bench.where("false")).count() == 0


# ---- segmentations ---------------------------------------------------------------------------------------------------

def test_round_trip_and_distinct(spark, docs_of, odd):
    docs = docs_of([*odd, (50, "a ▁ b  ▁▁c "), (51, " "), (52, "x" * 3000)])
    enc = sampling.encode(docs, k=3)
    got = collect(sampling.decode(enc))
    assert all(r["decodes"] for r in got)
    texts = {i: t or "" for i, t in [(r.doc_id, r.text) for r in docs.collect()] if i is not None}
    by = collections.defaultdict(list)
    for r in got:
        if r["doc_id"] is not None:
            assert r["text"] == texts[r["doc_id"]]
            by[r["doc_id"]].append(tuple(r["ids"]))
    assert all(len(set(by[i])) == len(by[i]) == 3 for i in (6, 7, 50)) and len(by[1]) == 1
    again = {(r.doc_id, r["sample"]): list(r.ids) for r in sampling.encode(docs.repartition(5), k=3).collect()}
    assert all(again[r["doc_id"], r["sample"]] == r["ids"] for r in got)


def test_sampling_follows_the_lattice():
    v = sampling.Vocabulary.load()

    def ways(u):
        if not u:
            return [((), 0.0)]
        return [((v.pieces[u[:k]][0], *s), v.pieces[u[:k]][1] + x) for k in range(1, len(u) + 1) if u[:k] in v.pieces for s, x in ways(u[k:])]

    units = [" the", " ab"]
    full = {a + b: x + y for a, x in ways(units[0]) for b, y in ways(units[1])}
    z = np.log(sum(np.exp(x) for x in full.values()))
    p = {k: float(np.exp(x - z)) for k, x in full.items()}
    lat = sampling.Lattice(v, units)
    start, n, seen = lat.root[[0, 1]], 3000, collections.Counter()
    for key in range(n):
        seeds = sampling.mix(np.repeat(np.array([key], np.uint64), 2)) + np.arange(2, dtype=np.uint64)
        drawn = [sampling.draw(lat, start, sampling.mix(seeds ^ sampling.mix(np.array([i + 1], np.uint64)))) for i in range(2)]
        s = sampling.Search(lat, key, start, drawn)
        (a, la, ga), (b, lb, gb) = s.run()
        a, b = tuple(lat.ids(a).tolist()), tuple(lat.ids(b).tolist())
        assert a != b and ga >= gb >= s.threshold and la == pytest.approx(np.log(p[a]), abs=1e-6) and lb == pytest.approx(np.log(p[b]), abs=1e-6)
        seen[a] += 1
    top = max(p, key=p.get)
    assert abs(seen[top] / n - p[top]) < 0.01


# ---- exact dedup and URLs --------------------------------------------------------------------------------------------

@pytest.mark.parametrize("name", list(queries.ORACLES))
def test_sql(spark, duck, sf_dir, name):
    assert plain(queries.QUERIES[name](spark, sf_dir).toPandas()) == plain(duck.execute(queries.ORACLES[name]).df())


def test_exact_dedup_odd_rows(spark, docs_of, odd):
    got = collect(exact.decisions(docs_of([*odd, (30, "onetwothreefourfive six  ")])))
    blank = [r for r in got if r["doc_id"] in (1, 2, 3)]
    assert {r["keep_id"] for r in blank} == {3} and {r["group_size"] for r in blank} == {3}
    words = [r for r in got if r["doc_id"] in (4, 30, None)]
    assert {r["keep_id"] for r in words} == {4} and {r["group_size"] for r in words} == {4} and sum(r["kept"] for r in words) == 1
    lean = {(r.doc_id, r.keep_id) for r in exact.decisions(docs_of(odd), all_hashes=False).collect()}
    assert lean == {(r.doc_id, r.keep_id) for r in exact.decisions(docs_of(odd)).collect()}
    assert {r.doc_id for r in exact.dedup(docs_of(odd)).collect()} == {3, 4, 5, 6, 7}
    assert exact.decisions(docs_of(odd).where("false")).count() == 0


def test_url_rules(spark):
    rules = [("com", "/", "block"), ("a.com", "/x/", "allow"), ("a.com", "/x/y", "block"), ("b.a.com", "/x/y/z", "allow")]
    t = urls.HostPathTrie(rules)
    cases = {
        "http://com/": "com/", "http://A.com/x/1": "a.com/x/", "https://a.com/x/yes?q": "a.com/x/y", "http://b.a.com/x/y/z#f": "b.a.com/x/y/z", "http://b.a.com/x/y/": "a.com/x/y", "http://xa.com/x/": "com/",
        "http://a.com": None, "nothing": None, None: None, "": None, "x://": None, "http://org/x": None,
    }
    for url, rule in cases.items():
        assert t.match(*urls.split_url(url))[0] == rule, url
    df = spark.createDataFrame([(i, u, "h") for i, u in enumerate(cases)], "page_id long, url string, host string")
    assert urls.judge(df, rules).count() == len(cases)
    assert urls.apply(df, rules).columns == ["page_id", "url", "host"] and urls.apply(df, rules).where("page_id = 0").count() == 0


def test_held_out_rows(spark, sf_dir):
    rows = queries.op4_weak_toxicity(spark, sf_dir).collect()
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) and r.predicted == int(r.score >= 0.3) for r in rows)


# ---- pipeline --------------------------------------------------------------------------------------------------------

def test_pipeline_equals_brute_force(spark, sf_dir):
    import corpus_pipeline

    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()]
    left = [(d, t) for d, t in docs if t and any(c.isalpha() for c in t)]
    groups = collections.defaultdict(list)
    for d, t in left:
        groups[re.sub("[\x20\x09-\x0D]+", "", t)].append((-len(t), d))
    keep = {min(g)[1] for g in groups.values()}
    left = [(d, t) for d, t in left if d in keep]
    roots = roots_of(left)
    left = [(d, t) for d, t in left if roots[d] == d]
    bad = {d for d, _ in slow_matches(left, items)}
    want = {d for d, _ in left if d not in bad}
    out = corpus_pipeline.run(spark, sf_dir)
    rows = out.collect()
    assert {r.doc_id for r in rows} == want and all(r.decodes for r in rows)
    assert 4 <= len(corpus_pipeline.STAGES) <= 5
