"""Personal data, and the terms around it that give it away.

Base spans come from patterns per kind, leftmost and non-overlapping, checked and never retried. The patterns run
over the bytes of a text in linear time: an address is looked for at each "@", a number at the start of its digits.

Information-theoretic part. Protected entities are what the base spans tell, at four levels: a span's value, its group
(an address's domain, a network, a card's issuer, a number's area: see `group`), its kind, and that there is personal
data at all. Terms (runs of letters and digits of at least MIN_TERM characters) of the same text, outside all spans,
may disclose them. Over the whole corpus a term t and an entity e meet in n(t, e) texts, t stands outside the spans
of df(t) texts, e in df(e), of N. The information that t gives about e is the pointwise mutual information
log(p(e | t) / p(e)); as a share of the information of e itself, -log p(e), it is 1 if t never stands without e.
A term discloses e if the share is at least DISCLOSE and no chance: were t independent of e, n(t, e) or more meetings
would have a probability of at most exp(-df(t) KL(n / df(t), p(e))), which must not exceed ERROR over the number of
all pairs of a term and an entity. Such terms are spans of the kind "term" wherever they stand outside base spans, in
texts without e too; from REMOVE on they are removed by `sanitised`, below it generalised to their shape.
Counts are over different texts, so that copies of one text don't make evidence.

Kinds are counted with the terms, within tasks. Pairs are made only of values and groups, and of those that can pass:
the test needs df(e) * -log p(e) >= L, its bound, and df(t) >= L / log N; the share needs
df(t) <= df(e) ** DISCLOSE * N ** (1 - DISCLOSE), as n(t, e) <= df(e). None that passes is lost.

Defined cases: a null text is empty and has no spans; repeated rows get equal results and count once; offsets are code
points, end exclusive; texts of any length; ties in a term's share don't matter, the largest counts; without personal
data, or with it in every text, nothing discloses; an empty table gives an empty result; other columns aren't read,
whatever their names.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import KeyTable, Tally, alone, chunks, keep, lowered, mix, span_hashes
from .toxicity import letter_spans

KINDS = ("email", "ip", "card", "phone")
ANY = len(KINDS)  # the kind of all
MIN_TERM = 4
ERROR = 0.05
DISCLOSE = 0.8
REMOVE = 0.95
MOST_TERMS = 2_000_000
FLUSH = 400_000

_DOMAIN = re.compile(rb"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = np.zeros(256, bool)
_LOCAL[[*range(48, 58), *range(65, 91), *range(97, 123), *b"._%+-"]] = True
# A digit before the start would have been part of an earlier try with the same outcome; possessive runs don't retry.
_IP = re.compile(rb"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(rb"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(rb"\+[0-9][ ().0-9-]+[0-9]")
_DIGIT = re.compile(rb"[0-9]")


def luhn(digits: bytes) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = c - 48
        if k % 2:
            d = d * 2 - 9 if d > 4 else d * 2
        total += d
    return total % 10 == 0


def _emails(text: bytes) -> Iterator[tuple[int, int]]:
    free, at = 0, text.find(b"@")
    while at >= 0:
        start = at
        while start > free and _LOCAL[text[start - 1]]:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at + 1)):
            yield start, m.end()
            free = m.end()
        at = text.find(b"@", max(at + 1, free))


def base_spans(text: bytes) -> list[tuple[int, int, int]]:
    """(kind, start, end) in bytes, by kind and start."""
    out = [(0, s, e) for s, e in _emails(text)]
    if not _DIGIT.search(text):
        return out
    for m in _IP.finditer(text):
        if all(int(x) <= 255 if len(x) < 20 else not x.strip(b"0") or int(x[-20:]) <= 255 and not x[:-20].strip(b"0") for x in m[0].split(b".")):
            out.append((1, *m.span()))
    for m in _CARD.finditer(text):
        digits = m[0].replace(b" ", b"").replace(b"-", b"")
        if 16 <= len(digits) <= 19 and luhn(digits):
            out.append((2, *m.span()))
    if b"+" in text:
        for m in _PHONE.finditer(text):
            if 8 <= sum(48 <= c <= 57 for c in m[0]) <= 15:
                out.append((3, *m.span()))
    return out


def entity(kind: int, value: bytes) -> bytes:
    """One spelling for an entity."""
    return b"%d:" % kind + (value.lower() if kind == 0 else value if kind == 1 else bytes(c for c in value if 48 <= c <= 57))


def group(kind: int, value: bytes) -> bytes:
    """What entities share: the domain, the first two numbers of an address, six digits of a card, four of a phone."""
    own = entity(kind, value)[2:]
    return b"%d~" % kind + (own.split(b"@", 1)[1] if kind == 0 else b".".join(own.split(b".")[:2]) if kind == 1 else own[: 6 if kind == 2 else 4])


def _terms(data: np.ndarray, at: np.ndarray, spans: list[list[tuple[int, int, int]]], points: np.ndarray) -> tuple[np.ndarray, ...]:
    """Start, end (in bytes), row and hash of each term outside the rows' spans; points: characters before each byte."""
    low = lowered(data)
    starts, ends, row = letter_spans(low, at)
    here = points[ends] - points[starts] >= MIN_TERM
    edges = np.array([(at[i] + a, at[i] + b) for i, s in enumerate(spans) for _, a, b in s], np.int64).reshape(-1, 2)
    if len(edges):
        depth = np.zeros(len(data) + 1, np.int64)
        np.add.at(depth, edges[:, 0], 1)
        np.add.at(depth, edges[:, 1], -1)
        covered = np.concatenate([[0], np.cumsum(np.cumsum(depth[:-1]) > 0)])
        here &= covered[ends] == covered[starts]
    starts, ends, row = starts[here], ends[here], row[here]
    with np.errstate(over="ignore"):
        return starts, ends, row, span_hashes(low, starts, ends)


def _scan(column: pa.Array) -> Iterator[tuple]:
    """start, end, text as bytes, offsets, base spans of each row, characters before each byte, and _terms."""
    for start, end, data, at in chunks(column):
        whole = data.tobytes()
        spans = [base_spans(whole[a:b]) for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
        points = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
        yield start, end, whole, at, spans, points, _terms(data, at, spans, points)


def _different(row: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The different hashes of each row."""
    order = np.lexsort((h, row))
    row, h = row[order], h[order]
    first = np.concatenate([[True], (h[1:] != h[:-1]) | (row[1:] != row[:-1])]) if len(h) else np.zeros(0, bool)
    return row[first], h[first]


def _lists(row: np.ndarray, values: pa.Array, n: int) -> pa.Array:
    """values, sorted by row, as one list a row."""
    return pa.ListArray.from_arrays(pa.array(np.searchsorted(row, np.arange(n + 1)), pa.int32()), values)


def found(docs: DataFrame) -> DataFrame:
    """text_id (a hash), kinds (a bit each), entities (values and groups) and terms: the different ones, as hashes;
    terms only where entities are."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start, end, whole, at, spans, _, (_, _, row, h) in _scan(batch[0]):
                n = end - start
                raw = [(i, f(k, whole[at[i] + a : at[i] + b])) for i, s in enumerate(spans) for k, a, b in s for f in (entity, group)]
                edges = np.concatenate([[0], np.cumsum([len(x) for _, x in raw])]).astype(np.int64)
                with np.errstate(over="ignore"):
                    e = mix(span_hashes(np.frombuffer(b"".join(x for _, x in raw), np.uint8), edges[:-1], edges[1:]))
                owner, e = _different(np.array([i for i, _ in raw], np.int64), e)
                kinds = _kinds(spans)
                private = row[kinds[row] > 0], h[kinds[row] > 0]
                row, h = _different(*private)
                yield pa.RecordBatch.from_arrays([batch[1].slice(start, n), pa.array(kinds), _lists(owner, pa.array(e.view(np.int64)), n), _lists(row, pa.array(h.view(np.int64)), n)], ["text_id", "kinds", "entities", "terms"])

    return docs.select("text", F.xxhash64("text").alias("text_id")).mapInArrow(run, "text_id long, kinds int, entities array<long>, terms array<long>")


def _kinds(spans: list[list[tuple[int, int, int]]]) -> np.ndarray:
    return np.array([sum({1 << k for k, _, _ in s}) | bool(s) << ANY for s in spans], np.int32)


def term_counts(docs: DataFrame) -> DataFrame:
    """t, df, and n0 .. n4: in how many different texts each term stands, and how many of them hold each kind and any
    (of rows that are different texts)."""
    each = [f"n{k}" for k in range(ANY + 1)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tallies = [Tally() for _ in range(ANY + 2)]  # the last one: all texts

        def rows() -> Iterator[pa.RecordBatch]:
            keys, df = tallies[-1].cleared()
            table = KeyTable(keys)
            columns = []
            for tally in tallies[:-1]:
                k, n = tally.cleared()
                column = np.zeros(len(keys), np.int64)
                column[table.find(k)] = n
                columns.append(column)
            for i in range(0, len(keys), 100_000):
                yield pa.RecordBatch.from_arrays([pa.array(c[i : i + 100_000]) for c in (keys.view(np.int64), df, *columns)], ["t", "df", *each])

        for b in batches:
            for _, _, _, _, spans, _, (_, _, row, h) in _scan(b[0]):
                row, h = _different(row, h)
                tallies[-1].add(h)
                kinds = _kinds(spans)
                for k in range(ANY + 1):
                    mine = h[kinds[row] >> k & 1 > 0]
                    if len(mine):
                        tallies[k].add(mine)
            if len(tallies[-1].keys) > FLUSH:  # sums follow in any case: what a task holds stays bounded
                yield from rows()
        yield from rows()

    counts = docs.select("text").mapInArrow(run, "t long, df long, " + ", ".join(f"{c} long" for c in each))
    return counts.groupBy("t").agg(*(F.sum(c).alias(c) for c in ("df", *each)))


def different_texts(marked: DataFrame, docs: DataFrame) -> DataFrame:
    """text, one row for each different text. Only texts with copies are dealt by their hash."""
    copied = keep(marked.groupBy("text_id").agg(F.count(F.lit(1)).alias("rows")).where("rows > 1").select("text_id"))
    copied = F.broadcast(copied) if copied.count() <= 1_000_000 else copied
    texts = docs.select("text", F.xxhash64("text").alias("text_id"))
    alone = texts.join(copied, "text_id", "left_anti")
    return alone.unionByName(texts.join(copied, "text_id", "left_semi").dropDuplicates(["text_id"])).select("text")


def disclosing(marked: DataFrame, docs: DataFrame, disclose: float = DISCLOSE, error: float = ERROR) -> DataFrame:
    """t, share: the terms that disclose, with their largest share. Texts count once: copies are known by the hash."""
    total = float(marked.select(F.countDistinct("text_id")).first()[0])
    texts = keep(marked.where("kinds > 0").dropDuplicates(["text_id"]))
    held = texts.select("text_id", F.explode("entities").alias("e"))
    entities = keep(held.groupBy("e").agg(F.count(F.lit(1)).alias("de")))
    counts = keep(term_counts(different_texts(marked, docs)))
    in_kind = texts.agg(*(F.coalesce(F.sum(F.shiftright("kinds", k).bitwiseAND(1)), F.lit(0)).alias(f"n{k}") for k in range(ANY + 1))).first()
    pairs = (entities.count() + ANY + 1) * counts.count()
    bound = float(np.log(max(pairs, 1) / error))
    p, q = F.col("de") / F.lit(total), F.col("n") / F.col("df")
    information = -F.log(p)
    # entities that can pass, and terms that can with any of them
    entities = keep(entities.where((F.col("de") < total) & (F.col("de") * information >= bound)).withColumn("most", F.pow(F.col("de").cast("double"), F.lit(disclose)) * total ** (1 - disclose) * (1 + 1e-9)))
    most = entities.agg(F.max("most")).first()[0] or 0.0
    able = counts.where((F.col("df") >= bound / np.log(max(total, 2.0))) & (F.col("df") <= most)).select("t", "df")
    terms = texts.select("text_id", F.explode("terms").alias("t")).join(able, "t")
    pairs = held.join(entities, "e").join(terms, "text_id").where(F.col("df") <= F.col("most"))
    met = pairs.groupBy("e", "t").agg(F.count(F.lit(1)).alias("n"), F.max("df").alias("df"), F.max("de").alias("de")).select("t", "n", "df", "de")
    kinds = F.explode(F.array(*(F.struct(F.col(f"n{k}").alias("n"), F.lit(in_kind[k]).cast("long").alias("de")) for k in range(ANY + 1))))
    met = met.unionByName(counts.select("t", "df", kinds.alias("x")).select("t", "x.n", "df", "x.de")).where((F.col("n") > 0) & (F.col("de") < total) & (q > p))
    chance = F.col("df") * (q * F.log(q / p) + F.when(q < 1, (1 - q) * F.log((1 - q) / (1 - p))).otherwise(F.lit(0.0)))
    share = met.where(chance >= bound).withColumn("share", F.least((F.log(q) + information) / information, F.lit(1.0)))
    return share.where(F.col("share") >= disclose).groupBy("t").agg(F.max("share").alias("share"))


def spans_of(docs: DataFrame, disclose: float = DISCLOSE, error: float = ERROR, most_terms: int = MOST_TERMS) -> DataFrame:
    """doc_id, text_id, counts of base spans, base, terms (array of (a, b, share), by place). Up to most_terms
    disclosing terms travel to the tasks; more are joined by hash to every term of the texts."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    pairs = alone(lambda: disclosing(keep(found(docs)), docs, disclose, error))
    few = pairs.count() <= most_terms
    known = pairs.toArrow() if few else None
    hashes, shares = (known["t"].to_numpy().view(np.uint64), known["share"].to_numpy()) if few and known.num_rows else (np.zeros(0, np.uint64), np.zeros(0))
    shared = docs.sparkSession.sparkContext.broadcast((few, hashes, shares))
    term = "a:int,b:int,share:double" if few else "a:int,b:int,t:bigint"
    schema = f"doc_id long, text_id long, n_email long, n_ip long, n_card long, n_phone long, base string, terms array<struct<{term}>>"
    names = ["doc_id", "text_id", "n_email", "n_ip", "n_card", "n_phone", "base", "terms"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        few, hashes, shares = shared.value
        table = KeyTable(hashes)
        for batch in batches:
            for start, end, _, at, spans, points, (first, last, row, h) in _scan(batch[2]):
                n = end - start
                zero = points[at[:-1]].tolist()
                base = [",".join(f"{KINDS[k]}:{points[at[i] + a] - zero[i]}:{points[at[i] + b] - zero[i]}" for k, a, b in s) for i, s in enumerate(spans)]
                counts = np.zeros((n, 4), np.int64)
                for i, s in enumerate(spans):
                    for k, _, _ in s:
                        counts[i, k] += 1
                value = h.view(np.int64)
                if few:
                    with np.errstate(over="ignore"):
                        place = table.find(h)
                    hit = place >= 0
                    first, last, row, value = first[hit], last[hit], row[hit], shares[place[hit]]
                own = points[at[row]]
                terms = pa.StructArray.from_arrays([pa.array(points[first] - own, pa.int32()), pa.array(points[last] - own, pa.int32()), pa.array(value)], ["a", "b", "share" if few else "t"])
                yield pa.RecordBatch.from_arrays([batch[0].slice(start, n), batch[1].slice(start, n), *(pa.array(c) for c in counts.T), pa.array(base, pa.string()), _lists(row, terms, n)], names)

    rows = docs.select("doc_id", F.xxhash64("text").alias("text_id"), "text").mapInArrow(run, schema)
    if few:
        return rows.withColumn("terms", F.when(F.size("terms") > 0, F.col("terms")))
    rows = keep(rows.withColumn("row", F.monotonically_increasing_id()))
    hits = rows.select("row", F.explode("terms").alias("x")).select("row", "x.*").join(pairs, "t")
    terms = hits.groupBy("row").agg(F.array_sort(F.collect_list(F.struct("a", "b", "share"))).alias("terms"))
    return rows.drop("terms").join(terms, "row", "left").drop("row")


def digests(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_term."""
    rows = spans_of(docs, **options)
    terms = F.array_join(F.transform(F.coalesce("terms", F.array().cast("array<struct<a:int,b:int,share:double>>")), lambda x: F.concat_ws(":", F.lit("term"), x["a"].cast("string"), x["b"].cast("string"))), ",")
    spans = F.concat_ws(",", F.nullif(F.col("base"), F.lit("")), F.nullif(terms, F.lit("")))
    return rows.select("doc_id", "n_email", "n_ip", "n_card", "n_phone", F.sha2(F.col("base").cast("binary"), 256).alias("base_sha256"), spans.alias("spans"), F.coalesce(F.size("terms"), F.lit(0)).cast("long").alias("n_term"))


def shape(word: str) -> str:
    """A term's generalisation: runs of capitals, small letters and digits."""
    kind = lambda c: "9" if c.isdigit() else "X" if c.isupper() else "x"
    out = ""
    for c in word:
        if not out.endswith(kind(c)):
            out += kind(c)
    return out


def sanitised(docs: DataFrame, remove: float = REMOVE, **options) -> DataFrame:
    """doc_id, text with base spans replaced by their kind, and terms removed or generalised."""
    # Rows with one doc_id and text have one result: no row number is carried from one scan to another.
    rows = spans_of(docs, **options).select(F.col("doc_id").alias("d"), "text_id", "base", "terms").dropDuplicates(["d", "text_id"])
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("own_id"))
    texts = own.join(rows, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("own_id") == F.col("text_id")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for text, base, terms in zip(b[1].to_pylist(), b[2].to_pylist(), b[3].to_pylist(), strict=True):
                if text is None:
                    out.append(None)
                    continue
                marks = [(int(x), int(y), f"[{k}]") for k, x, y in (s.split(":") for s in base.split(",") if s)]
                marks += [(t["a"], t["b"], "" if t["share"] >= remove else f"[{shape(text[t['a'] : t['b']])}]") for t in terms or []]
                parts, at = [], 0
                for x, y, new in sorted(marks, key=lambda m: (m[0], -m[1])):
                    if x >= at:
                        parts += (text[at:x], new)
                        at = y
                out.append("".join([*parts, text[at:]]))
            yield pa.RecordBatch.from_arrays([b[0], pa.array(out, pa.string())], ["doc_id", "text"])

    return texts.select("doc_id", "text", "base", "terms").mapInArrow(run, "doc_id long, text string")
