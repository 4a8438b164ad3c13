"""Personal data: base patterns, and terms that give a protected entity away.

Base spans are e-mail addresses, IP addresses, payment cards and phone numbers, leftmost and non-overlapping
within each kind; a match that fails its check is dropped and not retried.  Their values are the protected
entities.  Terms (lower-cased words of three letters at least) within ``REACH`` words of an entity are its
context.  With document counts over all documents,

    IC(e) = log(N / n(e)),   PMI(e, t) = log(N * n(e, t) / (n(e) * n(t)))

a term discloses e when PMI >= ``DISCLOSES`` * IC, for entities of a single document too: there, terms of at most
N^(1 - ``DISCLOSES``) documents.  In every document that holds e
each occurrence of such a term is a span of kind ``term``.  Sanitising replaces base spans by their kind, and a
disclosing term by its first ``STEM`` letters where that coarser term doesn't disclose e itself, else removes it.

Defined results: null counts as empty; an empty text has no spans; a repeated document counts again; spans are
code points with exclusive ends; base spans are never dropped because a term overlaps them, while terms inside
a base span are left to it.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left, bisect_right
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conflate.llm.common import small_batches
from conflate.plans.tables import broadcast_if_small, materialise

KINDS = ("email", "ip", "card", "phone")
REACH = 8
DISCLOSES = 0.8
STEM = 4
#: Context terms that are sent to every task; the documents of more are counted by a join.
TERMS_AT_ONCE = 300_000

_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
# a match can't begin inside a run of digits: an earlier start in that run would have matched or failed alike
_IP = re.compile(r"(?<![0-9])[0-9]++(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_WORD = re.compile(r"[^\W\d_]{3,}")


def _emails(text: str) -> list[tuple[int, int]]:
    out, floor, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > floor and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            out.append((start, m.end()))
            floor = m.end()
        at = text.find("@", max(at + 1, floor))
    return out


def _luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        x = ord(c) - 48
        total += x if i % 2 == 0 else (2 * x - 9 if x > 4 else 2 * x)
    return total % 10 == 0


def _byte(part: str) -> bool:
    part = part.lstrip("0")
    return len(part) < 3 or len(part) == 3 and part <= "255"


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end), in the order of the result."""
    out = [(a, 0, z) for a, z in _emails(text)]
    if "." in text:
        out += [(m.start(), 1, m.end()) for m in _IP.finditer(text) if all(map(_byte, m.group().split(".")))]
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 14:
            digits = m.group().replace(" ", "").replace("-", "")
            if 14 <= len(digits) <= 19 and _luhn(digits):
                out.append((m.start(), 2, m.end()))
    if "+" in text:
        out += [(m.start(), 3, m.end()) for m in _PHONE.finditer(text) if 10 <= sum(c.isdigit() for c in m.group()) <= 15]
    out.sort()
    return out


def entity(text: str, kind: int, start: int, end: int) -> str:
    value = text[start:end].lower()
    return f"{KINDS[kind]}:{value if kind < 2 else ''.join(c for c in value if c.isdigit())}"


class Inside:
    """Tells whether a stretch overlaps any of some spans, by one bisection: of the spans that begin before its end,
    the one that reaches furthest decides."""

    def __init__(self, spans: list[tuple[int, int]]):
        spans = sorted(spans)
        self.starts, self.reach, far = [s for s, _ in spans], [], 0
        for _, z in spans:
            far = max(far, z)
            self.reach.append(far)

    def __call__(self, start: int, end: int) -> bool:
        k = bisect_left(self.starts, end)
        return k > 0 and self.reach[k - 1] > start


def _context(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, entity, term) once for each document: '' stands for the entity itself; 'abcd*' for a stem."""
    for b in batches:
        keys, entities, terms = [], [], []
        for key, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            spans = base_spans(text or "")
            if not spans:
                continue
            inside = Inside([(s, z) for s, _, z in spans])
            words = list(_WORD.finditer(text))
            starts, ends = [m.start() for m in words], [m.end() for m in words]
            seen = set()
            for s, kind, z in spans:
                e = entity(text, kind, s, z)
                seen.add((e, ""))
                # REACH words to either side, however far away
                before, after = bisect_right(ends, s), bisect_left(starts, z)
                for m in words[max(0, before - REACH) : before] + words[after : after + REACH]:
                    if not inside(m.start(), m.end()):
                        t = m.group().lower()
                        seen.add((e, t))
                        if len(t) > STEM:
                            seen.add((e, t[:STEM] + "*"))
            for e, t in sorted(seen):
                keys.append(key)
                entities.append(e)
                terms.append(t)
        yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(entities, pa.string()), pa.array(terms, pa.string())], ["key", "entity", "term"])


def _document_counts(sent):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted = sent.value
        n: Counter = Counter()
        for b in batches:
            for text in b.column(0).to_pylist():
                words = set(_WORD.findall((text or "").lower()))
                words |= {w[:STEM] + "*" for w in words if len(w) > STEM}
                n.update(words if wanted is None else words & wanted)
            if wanted is None:  # any number of terms: what one batch counted goes out, and combines before the shuffle
                yield pa.RecordBatch.from_arrays([pa.array(list(n), pa.string()), pa.array(list(n.values()), pa.int64())], ["term", "df"])
                n.clear()
        yield pa.RecordBatch.from_arrays([pa.array(list(n), pa.string()), pa.array(list(n.values()), pa.int64())], ["term", "df"])

    return run


def disclosing(docs: DataFrame, context: DataFrame, discloses: float = DISCLOSES) -> DataFrame:
    """(entity, term, pmi, ic) of the terms that reveal an entity, stems included."""
    spark = docs.sparkSession
    joint = context.groupBy("entity", "term").agg(F.count("*").alias("n"))
    of_entity = joint.where("term = ''").select("entity", F.col("n").alias("ne"))
    pairs = materialise(joint.where(F.col("term") != "").join(of_entity, "entity"), "pairs")
    terms = materialise(pairs.select("term").distinct(), "terms")
    n_terms, n_docs = terms.count(), docs.count()
    # one scan either way: few terms go to every task, many meet the counts of all words in a join
    few = n_terms <= TERMS_AT_ONCE
    sent = spark.sparkContext.broadcast(frozenset(terms.toArrow().column(0).to_pylist()) if few else None)
    df = docs.select("text").mapInArrow(_document_counts(sent), "term string, df long").groupBy("term").agg(F.sum("df").alias("df"))
    df = df if few else df.join(terms, "term", "left_semi")
    n = F.lit(float(max(n_docs, 1)))
    scored = pairs.join(df, "term").select("entity", "term", F.log(n * F.col("n") / (F.col("ne") * F.col("df"))).alias("pmi"), F.log(n / F.col("ne")).alias("ic"))
    return scored.where((F.col("ic") > 0) & (F.col("pmi") >= F.lit(discloses) * F.col("ic")))


def _find(texts: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cols: list[list] = [[] for _ in range(7)]
            for text, terms in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
                text = text or ""
                base = base_spans(text)
                counts = Counter(k for _, k, _ in base)
                named = ",".join(f"{KINDS[k]}:{s}:{z}" for s, k, z in base)
                every = [(s, k, z, "") for s, k, z in base]
                if terms:
                    keep = {t["term"]: t["coarse"] for t in terms}
                    inside = Inside([(s, z) for s, _, z in base])
                    every += [(m.start(), len(KINDS), m.end(), keep[m.group().lower()]) for m in _WORD.finditer(text) if m.group().lower() in keep and not inside(m.start(), m.end())]
                    every.sort()
                for c, x in zip(cols, [*(counts[k] for k in range(4)), hashlib.sha256(named.encode()).hexdigest(), ",".join(f"{(*KINDS, 'term')[k]}:{s}:{z}" for s, k, z, _ in every), _rewrite(text, every) if texts else None]):
                    c.append(x)
            out = [b.column(0), *(pa.array(c, pa.int64()) for c in cols[:4]), pa.array(cols[4], pa.string()), pa.array(cols[5], pa.string())]
            names = ["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans"]
            if texts:
                out, names = [*out, pa.array(cols[6], pa.string())], [*names, "clean"]
            yield pa.RecordBatch.from_arrays(out, names)

    return run


def _rewrite(text: str, spans: list[tuple[int, int, int, str]]) -> str:
    out, at = [], 0
    for s, k, z, coarse in spans:
        if s < at:  # overlaps what is already gone
            at = max(at, z)
            continue
        out += [text[at:s], f"[{KINDS[k]}]" if k < len(KINDS) else coarse]
        at = z
    return "".join([*out, text[at:]])


def find(docs: DataFrame, texts: bool = False, discloses: float = DISCLOSES) -> DataFrame:
    """Spans of every document; ``texts`` adds the sanitised text as ``clean``."""
    small_batches(docs.sparkSession)
    keyed = docs.select("doc_id", "text", F.xxhash64("doc_id", "text").alias("key"))
    context = materialise(keyed.select("key", "text").mapInArrow(_context, "key long, entity string, term string"), "context")
    reveals = materialise(disclosing(docs, context, discloses).select("entity", "term"), "reveals")
    words, stems = reveals.where(~F.col("term").endswith("*")), reveals.where(F.col("term").endswith("*")).select("entity", F.expr(f"substring(term, 1, {STEM})").alias("stem"), F.lit(True).alias("tells"))
    words = words.withColumn("stem", F.substring("term", 1, STEM)).join(stems, ["entity", "stem"], "left")
    words = words.select("entity", "term", F.when(F.col("tells").isNotNull() | (F.char_length("term") <= STEM), "").otherwise(F.concat("stem", F.lit("*"))).alias("coarse"))
    held = context.where("term = ''").select("key", "entity").distinct().join(words, "entity")
    per_doc = held.groupBy("key", "term").agg(F.min("coarse").alias("coarse")).groupBy("key").agg(F.collect_list(F.struct("term", "coarse")).alias("terms"))
    per_doc = materialise(per_doc, "terms")
    rows = keyed.join(broadcast_if_small(per_doc), "key", "left").select("doc_id", "text", "terms")
    kind = docs.schema["doc_id"].dataType.simpleString()
    return rows.mapInArrow(_find(texts), f"doc_id {kind}, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string" + ", clean string" * texts)
