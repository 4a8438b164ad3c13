"""MinHash near-dedup with probability-weighted signatures.

Texts are lower-cased and cut into words of letters and digits; a text's elements are its runs of five words,
weighted by how often they occur.  Each element sends arrivals, a Poisson process at the rate of its weight,
to random registers; a register keeps its earliest arrival, and an element stops once its next arrival is
later than every register's.  Two texts agree in a register with the probability Jaccard similarity

    J(A, B) = sum over shared d of 1 / sum over d' of max(a[d'] / a[d], b[d'] / b[d]).

Registers are banded (``BANDS`` x ``ROWS``): at J = 0.8 a pair misses every band with chance 0.672^26 = 3e-5.
Candidates are then verified by the exact J of their whole texts, and links make classes.

Texts with equal words are one vertex from the start, so copies are never paired.  In a bucket of up to
``PAIRED`` different texts every pair is a candidate; in a larger one each text meets three leaders, then growing
shares of the texts meet all others, until every pair of the bucket was tested or is in one class.  Before that each
text meets the least one of its buckets, a few bands at a time, and pairs that classes join already are left out:
a class needs no more links than hold it together.

The growing shares' pairs are verified where two tests leave J = 0.8 possible.  The first never errs: each text has a
map of the parities of its elements' hashed places, and two maps differ in no more bits than the texts have elements
apart.  If p elements of A and q of B are apart, J(A, B) <= 1 / (1 + p / (|A| - p) + q / (|B| - q)), |A| and |B| being
the sums of the weights; so at J or more p + q is at most 2 (1 - J) / (1 + J) times the greater sum.  The second
serves long texts, whose maps are full: two bits of each of 128 registers differ in ``APART`` registers at most; at
J = 0.8 they differ in 19.2 on average and in more than 36 with chance 3e-5, the banding's own; at J = 0.5 in more
than 36 nearly always.

Rows are told apart by their place in one written scan.  Defined results: null, empty and wordless texts are classes
of their own; a text under five words is one element; repeated rows are members like any other, and one of them may
stay; a class is named by its least doc_id, a null one after all others; of rows with that doc_id the one of the
least text hash stays.  An empty table gives no rows; extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conflate.llm.common import crowds, keep_decided, small_batches, text_key
from conflate.llm.textkit import ALNUM, Words, mix, pieces, ranges, signed
from conflate.plans.graph import components
from conflate.plans.tables import broadcast_if_small, discard, materialise

WORDS = 5
SIMILAR = 0.8
BANDS = 26
ROWS = 5
PAIRED = 32
#: Bands, first and last, of the rounds in which members only meet the least one of their bucket.
STARRED = ((0, 1), (2, 25))
#: Registers whose two low bits may differ in a pair that is verified.
APART = 36
#: Longs of a sketch; each holds two bits of 32 registers.
SKETCHED = 4
#: Longs of a map of parities.
MAPPED = 16
_U = np.uint64


def elements(w: Words, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Document, hash (44 bits) and weight of the distinct elements of a piece, by document."""
    d, h = w.shingles(size)
    packed = (d.astype(_U) << _U(44)) | (h >> _U(20))
    packed.sort()
    first = np.flatnonzero(np.concatenate([[True], packed[1:] != packed[:-1]])) if len(packed) else np.zeros(0, np.int64)
    weight = np.diff(np.append(first, len(packed)))
    packed = packed[first]
    return (packed >> _U(44)).astype(np.int64), packed & _U((1 << 44) - 1), weight


def signatures(doc: np.ndarray, element: np.ndarray, weight: np.ndarray, n_docs: int, registers: int) -> np.ndarray:
    """Registers of every document; each holds the hash of the element that arrived first."""
    earliest = np.full(n_docs * registers, np.inf)
    holder = np.zeros(n_docs * registers, _U)
    live, at, turn = np.arange(len(doc)), np.zeros(len(doc)), 0
    while len(live):
        turn += 1
        r = mix(element[live] ^ mix(np.array([turn], _U)))
        at = at + -np.log(((r >> _U(11)).astype(np.float64) + 0.5) * 2.0**-53) / weight[live]
        slot = doc[live] * registers + ((mix(r) >> _U(32)) * _U(registers) >> _U(32)).astype(np.int64)
        np.minimum.at(earliest, slot, at)
        won = earliest[slot] == at
        holder[slot[won]] = element[live[won]]
        bound = earliest.reshape(n_docs, registers).max(1)
        go = at < bound[doc[live]]
        live, at = live[go], at[go]
    return holder.reshape(n_docs, registers)


def similarity(ea: np.ndarray, wa: np.ndarray, eb: np.ndarray, wb: np.ndarray) -> float:
    """Exact probability Jaccard of two weighted sets with sorted elements."""
    if not len(ea) or not len(eb):
        return 0.0
    both, ia, ib = np.intersect1d(ea, eb, assume_unique=True, return_indices=True)
    if not len(both):
        return 0.0
    a, b = wa[ia].astype(float), wb[ib].astype(float)
    only_a, only_b = wa.sum() - a.sum(), wb.sum() - b.sum()
    order = np.argsort(a / b, kind="stable")
    a, b = a[order], b[order]
    # for an element of ratio r, elements of a higher ratio count by a, those of a lower one by b
    above = only_a + a.sum() - (np.cumsum(a) - a)
    below = only_b + np.cumsum(b) - b
    return float((1 / (above / a + below / b)).sum())


def parities(doc: np.ndarray, element: np.ndarray, n_docs: int) -> np.ndarray:
    """Map of every document: whether an odd number of its elements falls on each of 64 x ``MAPPED`` places."""
    places = 64 * MAPPED
    at = ((mix(element ^ _U(0x9E3779B9)) >> _U(32)) * _U(places) >> _U(32)).astype(np.int64)
    odd = (np.bincount(doc * places + at, minlength=n_docs * places) & 1).astype(np.uint8)
    return np.packbits(odd.reshape(n_docs, places), axis=1, bitorder="little").view(_U).reshape(n_docs, MAPPED)


#: What is known of a text beside its bands: sketch, map and the sum of its weights.
KNOWN = [f"s{k}" for k in range(SKETCHED)] + [f"m{k}" for k in range(MAPPED)] + ["weight"]


def _sign(size: int, bands: int, rows: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi in pieces(b.column(2)):
                w = Words(b.column(2).slice(lo, hi - lo), ALNUM, fold=True)
                n = hi - lo
                d, e, weight = elements(w, size)
                regs = signatures(d, e, weight, n, bands * rows).reshape(n, bands, rows)
                key = np.full((n, bands), 0, _U)
                for i in range(rows):
                    key = mix(key * _U(31) + regs[:, :, i])
                key = mix(key + np.arange(bands, dtype=_U))
                full = w.counts() > 0
                place = ranges(w.counts()).astype(_U)
                h = [np.add.reduceat(np.append(mix(w.hash ^ mix(place * _U(2) + _U(k))), _U(0)), w.first[:-1]) if n else np.zeros(0, _U) for k in (1, 4)]
                flat = regs.reshape(n, bands * rows)[:, : SKETCHED * 32]
                low = np.zeros((n, SKETCHED * 32), _U)
                low[:, : flat.shape[1]] = (mix(flat) & _U(3)) << (np.arange(flat.shape[1], dtype=_U) % _U(32) * _U(2))
                sketch = np.bitwise_or.reduce(low.reshape(n, SKETCHED, 32), axis=2)
                known = [*sketch.T, *parities(d, e, n).T, np.bincount(d, weight, n).astype(np.int64)]
                empty = pa.array(~full)
                bands_col = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(full * bands)]).astype(np.int32)), pa.array(signed(key[full].ravel())))
                hashes = [pc.if_else(empty, None, pa.array(signed(x))) for x in h]
                yield pa.RecordBatch.from_arrays([*(b.column(c).slice(lo, n) for c in (0, 1, 3)), *hashes, bands_col, *(pa.array(np.ascontiguousarray(x).view(np.int64)) for x in known)], ["row", "doc_id", "th", "h1", "h2", "bands", *KNOWN])

    return run


def _alike(x: str, y: str, least: float = SIMILAR) -> str:
    """SQL: the sketches and the maps of x and y leave the similarity possible."""
    apart = [f"({x}.s{k} ^ {y}.s{k})" for k in range(SKETCHED)]
    sketched = " + ".join(f"bit_count(({d} | shiftrightunsigned({d}, 1)) & {0x5555555555555555})" for d in apart) + f" <= {APART}"
    mapped = " + ".join(f"bit_count({x}.m{k} ^ {y}.m{k})" for k in range(MAPPED))
    return f"{mapped} <= greatest({x}.weight, {y}.weight) * {2 * (1 - least) / (1 + least) + 1e-9}D and {sketched}"


def _verify(size: int, least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi in pieces(batch.column(2)):
                b = batch.slice(lo, hi - lo)
                sides = []
                for c in (2, 3):
                    d, e, weight = elements(Words(b.column(c), ALNUM, fold=True), size)
                    sides.append((e, weight, np.searchsorted(d, np.arange(b.num_rows + 1))))
                (ea, wa, fa), (eb, wb, fb) = sides
                s = np.array([similarity(ea[fa[i] : fa[i + 1]], wa[fa[i] : fa[i + 1]], eb[fb[i] : fb[i + 1]], wb[fb[i] : fb[i + 1]]) for i in range(b.num_rows)])
                keep = pa.array(np.flatnonzero(s >= least))
                yield pa.RecordBatch.from_arrays([b.column(0).take(keep), b.column(1).take(keep), pa.array(s).take(keep)], ["a", "b", "similarity"])

    return run


def _apart(members: DataFrame, found: DataFrame | None) -> DataFrame:
    """Members with the ``root`` of their class so far, of buckets that hold more than one class."""
    if found is None:
        return members.withColumn("root", F.col("rep"))
    roots = components(found).select(F.col("v").alias("rep"), "root")
    rooted = materialise(members.join(broadcast_if_small(roots), "rep", "left").withColumn("root", F.coalesce("root", "rep")), "rooted")
    mixed = rooted.groupBy("band", "bucket").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo <> hi").select("band", "bucket")
    return rooted.join(mixed, ["band", "bucket"], "left_semi")


def _stars(members: DataFrame, found: DataFrame | None) -> DataFrame:
    """Pairs (a < b) of each member with its bucket's least one, unless they are in one class already."""
    rooted = _apart(members, found)
    heads = rooted.groupBy("band", "bucket").agg(F.min(F.struct("rep", "root")).alias("h")).select("band", "bucket", "h")
    two = rooted.join(heads, ["band", "bucket"]).where("root <> h.root")
    return two.select(F.least("rep", "h.rep").alias("a"), F.greatest("rep", "h.rep").alias("b")).distinct()


def _candidates(members: DataFrame) -> DataFrame:
    """Pairs (a < b) of one bucket's members of different classes: all in a small bucket, leaders' in a large one."""
    rep, one = F.col("rep"), F.struct("rep", "root")
    sizes = members.groupBy("band", "bucket").agg(F.count("*").alias("n"), F.array(F.min(one), F.min_by(one, F.xxhash64(rep, F.lit(1))), F.min_by(one, F.xxhash64(rep, F.lit(2)))).alias("leaders")).where("n > 1")
    known = members.join(sizes, ["band", "bucket"])
    listed = known.where(F.col("n") <= PAIRED).groupBy("band", "bucket").agg(F.sort_array(F.collect_list(one)).alias("m"))
    small = listed.select(F.explode(F.expr("flatten(transform(m, (x, i) -> transform(filter(slice(m, i + 2, size(m)), y -> y.root <> x.root), y -> struct(x.rep as a, y.rep as b))))")).alias("p")).select("p.a", "p.b")
    large = known.where(F.col("n") > PAIRED).select("rep", "root", F.explode("leaders").alias("l")).where("root <> l.root").select(F.least("rep", "l.rep").alias("a"), F.greatest("rep", "l.rep").alias("b"))
    return small.unionByName(large).where("a <> b").distinct()


def links(docs: DataFrame, size: int = WORDS, least: float = SIMILAR, bands: int = BANDS, rows: int = ROWS) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(signature rows, text classes, verified links between text classes' representatives).

    A representative is the hash of one text of its class.
    """
    small_batches(docs.sparkSession)
    kind = docs.schema["doc_id"].dataType.simpleString()
    keyed = docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", "text", text_key(F.col("text")).alias("th"))
    signed_rows = materialise(keyed.mapInArrow(_sign(size, bands, rows), f"row long, doc_id {kind}, th long, h1 long, h2 long, bands array<long>, " + ", ".join(f"{c} long" for c in KNOWN)), "signatures")
    worded = signed_rows.where("h1 is not null")
    classes = materialise(worded.groupBy("h1", "h2").agg(F.min("th").alias("rep"), F.first("bands").alias("bands"), *[F.first(c).alias(c) for c in KNOWN]), "classes")
    members = classes.select("rep", F.posexplode("bands").alias("band", "bucket"))
    crowded = members.groupBy("band", "bucket").agg(F.count("*").alias("n")).where("n > 1").select("band", "bucket")
    members = materialise(members.join(crowded, ["band", "bucket"], "left_semi"), "members")
    texts = docs.select(text_key(F.col("text")).alias("key"), "text")

    def verified(pairs: DataFrame) -> DataFrame:
        ends = pairs.select(F.col("a").alias("key")).union(pairs.select("b")).distinct()
        held = materialise(texts.join(broadcast_if_small(ends), "key").dropDuplicates(["key"]), "texts")
        two = pairs.join(held.select(F.col("key").alias("a"), F.col("text").alias("ta")), "a").join(held.select(F.col("key").alias("b"), F.col("text").alias("tb")), "b")
        out = materialise(two.select("a", "b", "ta", "tb").mapInArrow(_verify(size, least), "a long, b long, similarity double"), "verified")
        discard(held)
        return out

    pairs, found = None, None
    for first, last in STARRED:
        star = _stars(members.where(f"band between {first} and {last}"), found)
        star = materialise(star if pairs is None else star.join(pairs, ["a", "b"], "left_anti"), "pairs")
        linked = verified(star)
        pairs, found = (star, linked) if pairs is None else (materialise(pairs.unionByName(star), "pairs"), materialise(found.unionByName(linked), "verified"))
    left = materialise(_candidates(_apart(members, found)).join(pairs, ["a", "b"], "left_anti"), "pairs")
    found, pairs = materialise(found.unionByName(verified(left)), "verified"), materialise(pairs.unionByName(left), "pairs")
    large = members.groupBy("band", "bucket").agg(F.count("*").alias("n")).where(F.col("n") > PAIRED).select("band", "bucket")
    crowd = members.join(large, ["band", "bucket"], "left_semi").join(classes.select("rep", *KNOWN), "rep")
    for more in crowds(crowd, ["band", "bucket"], "rep", lambda: found, lambda x, y: _alike(x, y, least)):
        more = materialise(more.join(pairs, ["a", "b"], "left_anti"), "pairs")
        if more.take(1):
            found, pairs = materialise(found.unionByName(verified(more)), "verified"), materialise(pairs.unionByName(more), "pairs")
    discard(members)
    discard(pairs)
    return signed_rows.withColumnRenamed("th", "key"), classes, found


def decisions(docs: DataFrame, **options) -> DataFrame:
    """doc_id, th, class_id, class_size and kept of every row of ``docs``."""
    rows, classes, found = links(docs, **options)
    roots = components(found).select(F.col("v").alias("rep"), "root")
    by_text = classes.select("h1", "h2", "rep").join(roots, "rep", "left").select("h1", "h2", F.coalesce("root", "rep").alias("root"))
    placed = materialise(rows.select("row", "doc_id", F.col("key").alias("th"), "h1", "h2").join(by_text, ["h1", "h2"], "left").select("row", "doc_id", "th", "root"), "placed")
    sizes = placed.where("root is not null").groupBy("root").agg(F.count("*").alias("class_size")).where("class_size > 1")
    grouped = placed.join(sizes.select("root"), "root", "left_semi")
    least = grouped.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("z"), F.col("doc_id").alias("id"), "th", "row")).alias("stays"))
    named = materialise(sizes.join(least, "root").select("root", "class_size", F.col("stays.id").alias("named"), F.col("stays.row").alias("stays")), "named")
    out = placed.join(named, "root", "left")
    alone = F.col("class_size").isNull()
    return out.select("doc_id", "th", F.when(alone, F.col("doc_id")).otherwise(F.col("named")).alias("class_id"), F.coalesce("class_size", F.lit(1)).cast("long").alias("class_size"), (alone | (F.col("row") == F.col("stays"))).alias("kept"))


def classes_of(docs: DataFrame, **options) -> DataFrame:
    """doc_id, class_id, class_size and kept (one row of each class) of every row."""
    return decisions(docs, **options).drop("th")


def dedup(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with one row of each class; all columns kept."""
    return keep_decided(docs, decisions(docs, **options).where("class_size > 1"))
