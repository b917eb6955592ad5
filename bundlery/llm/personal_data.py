"""Personal data: patterned identifiers, and terms that give them away.

Four kinds of identifier are found by pattern.  Beyond them, sanitisation is
information-theoretic: over the whole corpus, the documents with a term and an
identifier are counted against all documents with the term and all with the
identifier.  The pointwise mutual information of the two, smoothed, as a share
of the identifier's information content, says how much of it the term discloses:
1 means that the term occurs nowhere else.  Terms over the threshold become
spans in the documents of that identifier, and are generalised or removed with it.

Statistics are grouped counts on the executors.  Terms with more documents than
any identifier allows for are dropped before they meet identifiers.
"""

from __future__ import annotations

import re

import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .lineage import settle
from .textbits import slices, spare_name

#: Kinds in the order of ties, and the tag that takes the place of a span.
KINDS = ("email", "ip", "card", "phone", "term")
TAGS = {"email": "[EMAIL]", "ip": "[IP]", "card": "[CARD]", "phone": "[PHONE]", "term": "[TERM]"}
#: Documents of the corpus's own share that smooth the estimate for a term.
PRIOR = 0.5
#: Characters on either side of an identifier that tell copies of a passage.
NEAR = 60

_AT = re.compile(r"@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+")
_LOCAL_SET = frozenset("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789._%+-")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")
_TERM = re.compile(r"[^\W\d_]{4,}")


def _luhn(digits: str) -> bool:
    total = sum(map(int, digits[-1::-2]))
    return (total + sum(sum(divmod(2 * int(c), 10)) for c in digits[-2::-2])) % 10 == 0


def base_spans(text: str) -> list[tuple[int, str, int]]:
    """``start, kind, end`` of the patterned identifiers, by start and kind.

    Each kind is matched from the left without overlap; a match that fails its
    test is dropped and not tried again.  The patterns are written so that a
    text of any shape is read in linear time.
    """
    out: list[tuple[int, int, int]] = []
    if "@" in text:
        done = 0
        for m in _AT.finditer(text):
            start = at = m.start()
            while start > done and text[start - 1] in _LOCAL_SET:
                start -= 1
            if start < at:
                out.append((start, 0, m.end()))
                done = m.end()
    if _DIGIT.search(text):
        if "." in text:
            for m in _IP.finditer(text):
                if all(len(p.lstrip("0")) <= 3 and int(p) <= 255 for p in m[0].split(".")):
                    out.append((m.start(), 1, m.end()))
        for m in _CARD.finditer(text):
            if m.end() - m.start() >= 12:
                digits = m[0].replace(" ", "").replace("-", "")
                if 12 <= len(digits) <= 19 and _luhn(digits):
                    out.append((m.start(), 2, m.end()))
        if "+" in text:
            for m in _PHONE.finditer(text):
                if 9 <= sum(c.isdigit() for c in m[0]) <= 15:
                    out.append((m.start(), 3, m.end()))
    out.sort()
    return [(s, KINDS[k], e) for s, k, e in out]


def _key(text: str) -> int:
    return xxhash.xxh64_intdigest(text.encode("utf-8", "surrogatepass")) - (1 << 63)


def _source(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), *text_key(F.col("text").cast("string")))


def text_key(text: Column) -> list[Column]:
    """Two hashes, ``k1`` and ``k2``, that tell texts under one doc_id apart."""
    return [F.xxhash64(F.lit(i), text).alias(f"k{i}") for i in (1, 2)]


def _places(terms: DataFrame, name: str) -> DataFrame:
    """One row for each document of ``disclosing_terms``, its spans as an array in order."""
    return terms.groupBy("doc_id", "k1", "k2").agg(F.sort_array(F.collect_set(F.struct("start", "end"))).alias(name))


def _occurrences(docs: DataFrame, near: int) -> DataFrame:
    """Rows with identifiers: one record for each identifier, and one for each term.

    ``row`` numbers the table's rows.  ``context`` says what stands around the
    identifier in that row, and is null for terms, which come from the whole
    text; their places inside identifiers are left out.
    """
    fields = [("row", pa.int64()), ("doc_id", pa.int64()), ("k1", pa.int64()), ("k2", pa.int64()), ("key", pa.int64()), ("context", pa.int64()), ("starts", pa.list_(pa.int32())), ("ends", pa.list_(pa.int32()))]

    def made(rows):
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(zip(*rows), fields)], [n for n, _ in fields])

    def run(batches):
        row, rows = TaskContext.get().partitionId() << 40, []
        for batch in slices(batches):
            for doc, text, k1, k2 in zip(*(c.to_pylist() for c in batch.columns)):
                row += 1
                spans = base_spans(text) if text else []
                if not spans:
                    continue
                around: dict[int, set[str]] = {}
                for s, kind, e in spans:
                    around.setdefault(_key(f"{kind}:{text[s:e].lower()}"), set()).add(text[max(0, s - near) : e + near])
                rows += [(row, doc, k1, k2, k, _key("\n".join(sorted(v))), None, None) for k, v in around.items()]
                places: dict[str, tuple[list[int], list[int]]] = {}
                at = far = 0
                for m in _TERM.finditer(text):
                    while at < len(spans) and spans[at][0] < m.end():
                        far, at = max(far, spans[at][2]), at + 1
                    starts, ends = places.setdefault(m[0].lower(), ([], []))
                    if far <= m.start():
                        starts.append(m.start())
                        ends.append(m.end())
                rows += [(row, doc, k1, k2, _key(w), None, *x) for w, x in places.items()]
                if len(rows) > 20_000:
                    yield made(rows)
                    rows = []
        if rows:
            yield made(rows)

    return _source(docs).mapInArrow(run, "row long, doc_id long, k1 long, k2 long, key long, context long, starts array<int>, ends array<int>")


def _document_counts(docs: DataFrame) -> DataFrame:
    """``term, docs``: rows with each term."""

    def run(batches):
        counts, known = {}, {}
        for batch in slices(batches):
            for text in batch.column(1).to_pylist():
                for word in {w.lower() for w in set(_TERM.findall(text))} if text else ():
                    key = known.get(word)
                    if key is None:
                        if len(known) >= 100_000:
                            known.clear()
                        key = known[word] = _key(word)
                    counts[key] = counts.get(key, 0) + 1
                if len(counts) > 100_000:
                    yield pa.RecordBatch.from_arrays([pa.array(counts.keys(), pa.int64()), pa.array(counts.values(), pa.int64())], ["term", "docs"])
                    counts = {}
        if counts:
            yield pa.RecordBatch.from_arrays([pa.array(counts.keys(), pa.int64()), pa.array(counts.values(), pa.int64())], ["term", "docs"])

    return _source(docs).mapInArrow(run, "term long, docs long").groupBy("term").agg(F.sum("docs").alias("docs"))


def disclosing_terms(docs: DataFrame, threshold: float = 0.9, prior: float = PRIOR, near: int = NEAR) -> DataFrame:
    """``doc_id, k1, k2, start, end`` of terms that disclose an identifier of their document.

    ``k1`` and ``k2`` are the document's ``text_key``, so documents with one doc_id
    keep their own spans.

    Every identifier is judged, with every term of its documents.  The chance of
    the identifier given the term is smoothed by ``prior`` documents of the
    corpus's own share, so that less is concluded from one document than from
    many; documents with the same surroundings of ``near`` characters are copies
    of one passage and count once.
    """
    spark = docs.sparkSession
    seen = settle(_occurrences(docs, near))
    marks = seen.where(F.col("context").isNotNull()).select("row", F.col("key").alias("entity"), "context")
    terms = seen.where(F.col("context").isNull()).select("row", "doc_id", "k1", "k2", F.col("key").alias("term"), "starts", "ends")
    marks = marks.join(marks.groupBy("entity", "context").agg(F.min("row").alias("passage")), ["entity", "context"])
    # identifiers of the same rows and passages have the same terms: one of them stands for all
    own = marks.groupBy("entity").agg(F.count("*").alias("own"), F.bit_xor(F.xxhash64("row", "passage")).alias("sign"))
    own = settle(own.groupBy("sign", "own").agg(F.min("entity").alias("entity")))
    total, most = docs.count(), own.agg(F.max("own")).first()[0]
    if most is None:
        return spark.createDataFrame([], "doc_id long, k1 long, k2 long, start long, end long")

    def room(own):
        """The most documents that a term can have and still disclose an identifier of ``own``."""
        return (own + prior * own / total) * F.pow(F.lit(total) / own, F.lit(1 - threshold)) - prior + 1e-6

    rare = _document_counts(docs).where(F.col("docs") <= room(F.lit(most)))
    judged = marks.join(own, "entity").select("row", "entity", "passage", "own")
    pairs = settle(terms.select("row", "term").join(rare, "term").join(judged, "row").where(F.col("docs") <= room(F.col("own"))))
    each = pairs.groupBy("entity", "term", "passage").agg(F.count("*").alias("n"), F.min("docs").alias("docs"), F.min("own").alias("own"))
    known = each.groupBy("entity", "term").agg(F.sum("n").alias("both"), F.count("*").alias("passages"), F.min("docs").alias("docs"), F.min("own").alias("own"))
    share = F.col("own") / F.lit(float(total))
    given = (F.col("passages") + prior * share) / (F.col("passages") + F.col("docs") - F.col("both") + prior)
    found = known.where((share < 1) & (F.log2(given / share) >= threshold * -F.log2(share))).select("entity", "term")
    hits = pairs.join(found, ["entity", "term"]).select("row", "term").distinct()
    places = terms.join(hits, ["row", "term"]).select("doc_id", "k1", "k2", F.explode(F.arrays_zip("starts", "ends")).alias("x"))
    return places.select("doc_id", "k1", "k2", F.col("x.starts").cast("long").alias("start"), F.col("x.ends").cast("long").alias("end")).distinct()


def _same(a: tuple[str, str, str], b: tuple[str, str, str]) -> Column:
    """Whether two rows are of one document; a null doc_id is one too."""
    return F.col(a[0]).eqNullSafe(F.col(b[0])) & (F.col(a[1]) == F.col(b[1])) & (F.col(a[2]) == F.col(b[2]))


def find_personal_data(docs: DataFrame, threshold: float = 0.9, prior: float = PRIOR) -> DataFrame:
    """``doc_id, base, terms`` of each row: spans by pattern, and disclosing terms.

    ``base`` holds ``start, kind, end`` in code points, end exclusive, in order;
    ``terms`` holds ``start, end`` or null.  Null texts count as empty.  Repeated
    rows give repeated results.
    """

    def run(batches):
        for batch in slices(batches):
            spans = [base_spans(t) if t else [] for t in batch.column(1).to_pylist()]
            kind = pa.list_(pa.struct([("start", pa.int64()), ("kind", pa.string()), ("end", pa.int64())]))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), batch.column(3), pa.array([[{"start": s, "kind": k, "end": e} for s, k, e in x] for x in spans], kind)], ["id", "a", "b", "base"])

    base = _source(docs).mapInArrow(run, "id long, a long, b long, base array<struct<start:long,kind:string,end:long>>")
    terms = _places(disclosing_terms(docs, threshold, prior), "terms")
    return base.join(terms, _same(("id", "a", "b"), ("doc_id", "k1", "k2")), "left").select(F.col("id").alias("doc_id"), "base", "terms")


def sanitise(docs: DataFrame, threshold: float = 0.9, prior: float = PRIOR, remove_terms: bool = False) -> DataFrame:
    """``docs`` with identifiers and disclosing terms replaced in ``text``.

    Identifiers become the tag of their kind, terms a general tag or nothing.
    Where spans overlap, the one that starts first (then the first kind) wins and
    the rest of the overlapped text goes with it.  All columns stay; texts
    without spans, and null texts, are unchanged.
    """
    whole, extra = (spare_name(docs.columns, n) for n in ("_text", "_terms"))
    own, of = ([spare_name([*docs.columns, whole, extra], n + side) for n in ("_id", "_k1_", "_k2_")] for side in ("own", "of"))
    k1, k2 = text_key(F.col("text").cast("string"))
    marked = docs.select("*", F.col("text").cast("string").alias(whole), F.col("doc_id").cast("long").alias(own[0]), k1.alias(own[1]), k2.alias(own[2]))
    per = _places(disclosing_terms(docs, threshold, prior), extra).select(extra, *[F.col(a).alias(b) for a, b in zip(("doc_id", "k1", "k2"), of)])
    joined = marked.join(per.hint("shuffle_hash"), _same(own, of), "left").drop(*own, *of)
    types = {f.name: f for f in docs.schema.fields}

    def run(batches):
        for batch in slices(batches):
            names = batch.schema.names
            text, terms = batch.column(names.index(whole)).to_pylist(), batch.column(names.index(extra)).to_pylist()
            out = []
            for t, beside in zip(text, terms):
                spans = base_spans(t) if t else []
                if beside:
                    spans = sorted(spans + [(x["start"], "term", x["end"]) for x in beside])
                if spans:
                    parts, at = [], 0
                    for s, kind, e in spans:
                        if s >= at:
                            parts += [t[at:s], "" if kind == "term" and remove_terms else TAGS[kind]]
                        at = max(at, e)
                    t = "".join(parts) + t[at:]
                out.append(t)
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.string()) if n == "text" else batch.column(names.index(n)) for n in types], list(types))

    return joined.mapInArrow(run, docs.schema)
