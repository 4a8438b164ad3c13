"""Near-dedup of many small groups that share only one crowded bucket."""

import random

import numpy as np

from conflate.llm import probminhash


def test_many_groups_in_one_bucket(spark, docs_of):
    common = " ".join(f"c{i}" for i in range(80))
    rows = []
    for i in range(60):
        own = [f"g{i}x{j}" for j in range(20)]
        rows += [(2 * i, f"{common} {' '.join(own)}"), (2 * i + 1, f"{common} {' '.join(own[:-1])} z{i}")]
    # one band of one register: most texts stand in few large buckets
    signed, classes, found = probminhash.links(docs_of(rows), bands=1, rows=1)
    bands = {r.rep: r.bands[0] for r in classes.collect()}
    keys = {r.key: r.doc_id for r in signed.collect()}
    got = {tuple(sorted((keys[r.a], keys[r.b]))) for r in found.collect()}
    where = {keys[k]: b for k, b in bands.items()}
    want = {(2 * i, 2 * i + 1) for i in range(60) if where[2 * i] == where[2 * i + 1]}
    assert len(want) > 40 and want <= got


def test_copies_of_one_text_are_not_paired_with_each_other(spark, docs_of):
    base = [f"w{i}" for i in range(400)]
    rows = [(i, " ".join(base[: 9 * i] + [f"x{i}"] + base[9 * i :])) for i in range(30)]
    rows += [(100 + i, " ".join(f"o{i}y{j}" for j in range(50))) for i in range(5)]
    _, classes, found = probminhash.links(docs_of(rows))
    # a chain or star of 30 texts has 29 links; all their pairs are 435
    assert classes.count() == 35 and 29 <= found.count() <= 100
    got = {r.doc_id: (r.class_id, r.class_size) for r in probminhash.classes_of(docs_of(rows)).collect()}
    assert got == {i: (0, 30) if i < 30 else (i, 1) for i, _ in rows}


def test_texts_outside_a_class_are_ruled_out_without_a_pair_each(spark, docs_of, monkeypatch):
    """Texts of one origin: 80 with one changed word make a class, 80 with four are alone, all in few large buckets."""
    r, base, rows = random.Random(3), [f"w{i}" for i in range(150)], []
    for i in range(160):
        words = list(base)
        for k in range(1 if i < 80 else 4):
            words[r.randrange(k * 37 + 5, k * 37 + 32)] = f"x{i}y{k}"
        rows.append((i, " ".join(words)))
    tested, write = [], probminhash.materialise

    def counting(df, label):
        out = write(df, label)
        tested.append(out.count() if label == "pairs" else 0)
        return out

    monkeypatch.setattr(probminhash, "materialise", counting)
    got = {x.doc_id: x.class_size for x in probminhash.classes_of(docs_of(rows), bands=2, rows=1).collect()}
    assert got == {i: 80 if i < 80 else 1 for i in range(160)}
    # the last table holds all pairs tested; the class with all others would be 6,400
    assert 120 <= max(tested) < 1500


def test_maps_rule_out_no_similar_pair(spark):
    r = random.Random(8)
    base = [r.randrange(1 << 43) for _ in range(300)]
    sets = []
    for i in range(120):
        own = r.sample(base, r.randint(20, 300)) if i % 3 else base[: r.randint(240, 300)]
        own = {e: r.choice((1, 1, 1, 2, 5)) for e in own + [r.randrange(1 << 43) for _ in range(r.randint(0, 30))]}
        sets.append((np.array(sorted(own), np.uint64), np.array([own[e] for e in sorted(own)])))
    doc = np.repeat(np.arange(len(sets)), [len(e) for e, _ in sets])
    maps = probminhash.parities(doc, np.concatenate([e for e, _ in sets]), len(sets))
    close = out = 0
    for i in range(len(sets)):
        for j in range(i):
            (ea, wa), (eb, wb) = sets[i], sets[j]
            apart = sum(int(x).bit_count() for x in maps[i] ^ maps[j])
            assert apart <= len(np.setxor1d(ea, eb))
            s = probminhash.similarity(ea, wa, eb, wb)
            bound = 2 * (1 - s) / (1 + s) * max(wa.sum(), wb.sum())
            assert apart <= bound + 1e-6
            close, out = close + (s >= 0.5), out + (apart > 2 / 9 * max(wa.sum(), wb.sum()))
    assert close > 20 and out > 1000
