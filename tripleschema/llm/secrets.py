"""Secret scan with corpus-wide ownership frequency.

Three base kinds are always reported.  Further candidates (issued token formats, mixed random-looking strings) count
unless they are examples: an example that many owners have copied from documentation is known by the number of distinct
owners and repositories that hold it in the whole corpus.  A string with few owners may be a live key in a copied page.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tripleschema.llm.common import prepare, slices, spread_join, written

#: Patterns and least lengths of the base kinds, in their order.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ASSIGN_WORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")
ISSUED = re.compile(r"gh[pousr]_[A-Za-z0-9]{36,}|xox[abprs]-[A-Za-z0-9-]{10,}|eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]*|AIza[A-Za-z0-9_-]{35}|sk_live_[A-Za-z0-9]{16,}")
MIXED = re.compile(r"[A-Za-z0-9+/_=-]{20,}")

KINDS = ("assign", "access", "hex", "issued", "mixed")
BASE = KINDS[:3]
EXAMPLE_OWNERS = 3  # with so many owners a string is an example that people copy
LEAST_BITS = 3.5  # entropy of a character of a mixed candidate

SPAN = "struct<kind:int,start:int,stop:int,hash:string>"
_ARROW = pa.list_(pa.struct([("kind", pa.int32()), ("start", pa.int32()), ("stop", pa.int32()), ("hash", pa.string())]))


def _hash(value: str) -> str:
    return hashlib.sha256(value.encode()).hexdigest()[:32]


def base_spans(text: str) -> list[tuple[int, int, int, str]]:
    """(kind, start, stop, value) of the base kinds, by start and kind: leftmost matches, the short ones dropped."""
    out = []
    lower = text.lower()
    if any(w in lower for w in ASSIGN_WORDS):
        out += [(0, *m.span(), m[2]) for m in ASSIGN.finditer(text) if len(m[2]) >= 12]
    if "AKIA" in text:
        out += [(1, *m.span(), m[0]) for m in ACCESS.finditer(text) if m.end() - m.start() >= 18]
    out += [(2, *m.span(), m[0]) for m in HEX.finditer(text)]
    return sorted(out, key=lambda x: (x[1], x[0]))


def random_looking(value: str) -> bool:
    kinds = any(c.isdigit() for c in value) + any(c.isupper() for c in value) + any(c.islower() for c in value)
    return kinds == 3 and -sum(n / len(value) * math.log2(n / len(value)) for n in Counter(value).values()) >= LEAST_BITS


def further_spans(text: str, base: list[tuple]) -> list[tuple[int, int, int, str]]:
    """Candidates outside the base spans; a mixed one must not overlap an issued one."""
    taken = [(a, b) for _, a, b, _ in base]
    out = []
    for kind, found in ((3, ISSUED.finditer(text)), (4, MIXED.finditer(text))):
        for m in found:
            a, b = m.span()
            if (kind == 3 or random_looking(m[0])) and not any(a < y and x < b for x, y in taken):
                out.append((kind, a, b, m[0]))
                taken.append((a, b))
    return out


def _scan(carried: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, text=carried):
            spans = []
            for text in part.column(carried).to_pylist():
                base = base_spans(text or "")
                spans.append([{"kind": k, "start": a, "stop": b, "hash": _hash(v)} for k, a, b, v in [*base, *further_spans(text or "", base)]])
            yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(part.num_columns)), pa.array(spans, _ARROW)], [*part.schema.names, "__spans"])

    return run


def candidates(docs: DataFrame, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """The columns ``keep`` of each row and ``__spans``, all base and further candidates of its whole text."""
    prepare(docs.sparkSession)
    keep = [c for c in keep or docs.columns if c != text_col]
    rows = docs.select(*keep, text_col)
    rows = rows.withColumn(text_col, F.col(text_col).cast("string"))
    return rows.mapInArrow(_scan(len(keep)), ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema) + f", __spans array<{SPAN}>")


def ownership(found: DataFrame, owner: str, repo: str) -> DataFrame:
    """``hash, n_owners, n_repos, n`` (occurrences) over the whole corpus; a null owner or repository is one unknown one."""
    each = found.select(F.explode("__spans.hash").alias("hash"), F.coalesce(owner, F.lit("")).alias("o"), F.coalesce(repo, F.lit("")).alias("r"))
    each = each.groupBy("hash", "o", "r").agg(F.count("*").alias("n")).groupBy("hash", "o").agg(F.count("*").alias("n_repos"), F.sum("n").alias("n"))
    return each.groupBy("hash").agg(F.count("*").alias("n_owners"), F.sum("n_repos").alias("n_repos"), F.sum("n").alias("n"))


def judged(found: DataFrame, owner: str, repo: str) -> DataFrame:
    """``__rid, spans`` of the rows with a span, spans as structs with owners and verdict, in order.

    ``found`` must be a written table with a unique ``__rid``.  A span is live (one owner), shared, or an example (many
    owners).  Base spans all stay, whatever their verdict; further ones stay unless they are examples."""
    owners = written(ownership(found, owner, repo), "owners")
    each = spread_join(found.select("__rid", F.explode("__spans").alias("s")).select("__rid", "s.*"), owners, ["hash"], "n")
    verdict = F.when(F.col("n_owners") == 1, "live").when(F.col("n_owners") < EXAMPLE_OWNERS, "shared").otherwise("example").alias("verdict")
    each = each.select("__rid", F.struct("start", "kind", "stop", "hash", "n_owners", "n_repos", verdict).alias("s")).where((F.col("s.kind") < len(BASE)) | (F.col("s.verdict") != "example"))
    return each.groupBy("__rid").agg(F.sort_array(F.collect_list("s")).alias("spans"))


def _numbered(found: DataFrame, name: str) -> DataFrame:
    return written(found.withColumn("__rid", F.monotonically_increasing_id()), name)


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", owner_col: str = "source", repo_col: str = "source") -> DataFrame:
    """``doc_id, spans`` for each row: all reported spans of its whole text with kind, place, hash and ownership.

    Kinds are numbers into KINDS, places are code points with an exclusive end.  The text is read once; only hashes of
    candidates are shuffled, counted by owner and repository where they are found; a string that stands in a third of
    all rows meets its counts where its rows are.  Null and empty texts have no spans; rows with null or repeated ids
    stay apart; extra columns are not read; an empty table gives no rows.
    """
    part = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(owner_col).cast("string").alias("owner"), F.col(repo_col).cast("string").alias("repo"), F.col(text_col).alias("text"))
    found = _numbered(candidates(part).drop("text"), "secrets")
    spans = judged(found.where(F.size("__spans") > 0), "owner", "repo")
    return found.select("doc_id", "__rid").join(spans, "__rid", "left").select("doc_id", F.coalesce("spans", F.array()).alias("spans"))


def _redact(text_at: int, spans_at: int, mark: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, text=text_at):
            out = []
            for text, spans in zip(part.column(text_at).to_pylist(), part.column(spans_at).to_pylist(), strict=True):
                if text and spans:
                    pieces, at = [], 0
                    for s in sorted(spans, key=lambda s: (s["start"], s["stop"])):
                        if s["stop"] > at:
                            pieces += [text[at : s["start"]], mark] if s["start"] >= at else []
                            at = s["stop"]
                    text = "".join([*pieces, text[at:]])
                out.append(text)
            cols = [part.column(i) for i in range(part.num_columns) if i != spans_at]
            cols[text_at] = pa.array(out, pa.string())
            yield pa.RecordBatch.from_arrays(cols, [n for i, n in enumerate(part.schema.names) if i != spans_at])

    return run


def redacted(docs: DataFrame, text_col: str = "text", owner_col: str = "source", repo_col: str = "source", mark: str = "[secret]") -> DataFrame:
    """``docs`` with every reported span replaced by ``mark``; all rows and columns stay, null texts stay null.

    Only rows with a further candidate wait for the ownership counts; the others are rewritten where they are."""
    columns = docs.columns
    name = {c: f"c{i}" for i, c in enumerate(columns)}  # no name of a document column can clash with ours
    rows = docs.select(*(F.col(c).alias(n) for c, n in name.items()))
    found = _numbered(candidates(rows, name[text_col]).select(*name.values(), "__spans"), "secrets")
    further = F.exists("__spans", lambda s: s["kind"] >= len(BASE))
    places = "array<struct<start:int,stop:int>>"
    slim = lambda c: F.transform(c, lambda s: F.struct(s["start"].alias("start"), s["stop"].alias("stop")))
    with_spans = found.where(F.size("__spans") > 0)
    waiting = found.where(further).join(judged(with_spans, name[owner_col], name[repo_col]), "__rid", "left").withColumn("__cut", F.coalesce(slim("spans"), F.array().cast(places)))
    ready = found.where(~further).withColumn("__cut", slim("__spans"))
    cut = waiting.select(*name.values(), "__cut").unionByName(ready.select(*name.values(), "__cut"))
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in cut.schema if f.name != "__cut")
    done = cut.mapInArrow(_redact(columns.index(text_col), len(columns), mark), schema)
    return done.select(*(F.col(n).alias(c) for c, n in name.items()))
