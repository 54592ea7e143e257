"""Quality classifier: document evidence combined with host and path posteriors by hierarchical empirical Bayes.

Document evidence comes from a logistic model over the presence of character 4-grams and binned text statistics, fitted
on a bounded sample of labelled rows.  Two things are judged: low quality and toxicity.  Over the whole corpus the
outcomes (labels where there are some, else the evidence) are summed by path and host; a path's rate is shrunk toward
its host's and a host's toward the global one, the more the fewer documents it has, with strengths estimated from the
spread between hosts and between paths.  A document's log odds move by the log odds of its path over the global ones.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tripleschema.llm.common import numbered, prepare, relieve, slices, spread_join, without, written

SAMPLE = 4000  # labelled rows that the model is fitted on, at most
HASH_BITS = 18
GRAM = 4
FEATURES = 256  # grams kept for each judgement
BINS = 8
RIDGE = 1.0
HEADS = ("low", "toxic")
REJECT = 0.5  # posterior probability from which a document is rejected


# -- features


def statistics(text: str, points: np.ndarray) -> np.ndarray:
    """Length, compressibility and shares of kinds of characters."""
    n = max(1, len(points))
    raw = text.encode("utf-8", "surrogatepass")
    upper = int(((points >= 65) & (points <= 90)).sum() + ((points >= 0xC0) & (points <= 0xDE)).sum())
    digit = int(((points >= 48) & (points <= 57)).sum())
    space = int(((points == 32) | ((points >= 9) & (points <= 13))).sum())
    mark = int(((points > 32) & (points < 127)).sum()) - digit - int(((points | 32) - 97 < 26).sum())
    return np.array([np.log1p(len(points)), len(zlib.compress(raw, 1)) / max(64, len(raw)), upper / n, digit / n, mark / n, (n - space) / (space + 1)])


def code_points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")


def grams(text: str) -> np.ndarray:
    """Hashed character grams of the lower-case text, white space as a space, one at each place."""
    p = code_points(" " + text.lower() + " ")
    p = np.where((p >= 9) & (p <= 13), np.uint32(32), p)
    n = len(p) - GRAM + 1
    if n <= 0:
        return np.zeros(0, np.uint32)
    h = p[:n] * np.uint32(0x9E3779B1)
    for j in range(1, GRAM):
        h = (h ^ p[j : j + n]) * np.uint32(0x85EBCA6B)
        h ^= h >> np.uint32(15)
    return h & np.uint32((1 << HASH_BITS) - 1)


def _sample_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in slices(batches, text=0):
        texts = [t or "" for t in part.column(0).to_pylist()]
        found = [np.unique(grams(t)).astype("<u4").tobytes() for t in texts]
        stats = [statistics(t, code_points(t)).tolist() for t in texts]
        yield pa.RecordBatch.from_arrays([part.column(1), part.column(2), pa.array(found, pa.binary()), pa.array(stats, pa.list_(pa.float64()))], ["low", "toxic", "grams", "stats"])


# -- the document model


class Model:
    """Weights of the chosen grams and statistics bins, for both judgements."""

    def __init__(self, chosen: np.ndarray, edges: list[np.ndarray], weights: np.ndarray, bias: np.ndarray):
        self.chosen, self.edges, self.weights, self.bias = chosen, edges, weights, bias
        self.column = np.full(1 << HASH_BITS, -1, np.int32)
        self.column[chosen] = np.arange(len(chosen))

    def bins(self, stats: np.ndarray) -> np.ndarray:
        at = [len(self.chosen) + i * (BINS + 1) + int(np.searchsorted(e, v)) for i, (e, v) in enumerate(zip(self.edges, stats, strict=True))]
        return np.array(at, np.int64)

    def evidence(self, text: str) -> np.ndarray:
        """Log odds of each judgement."""
        hit = self.column[grams(text)]
        on = np.concatenate([np.unique(hit[hit >= 0]), self.bins(statistics(text, code_points(text)))])
        return self.bias + self.weights[on].sum(axis=0)


def fit(rows: list[tuple[int | None, int | None, bytes, list[float]]]) -> Model:
    """Fit on (low, toxic, gram ids, statistics); a judgement without both outcomes gets its prior only."""
    n_bins = 6 * (BINS + 1)
    present = [np.frombuffer(g, "<u4").astype(np.int64) for _, _, g, _ in rows]
    stats = np.array([s for *_, s in rows], float).reshape(len(rows), 6)
    edges = [np.unique(np.quantile(stats[:, i], np.linspace(0, 1, BINS + 1)[1:-1])) if len(rows) else np.zeros(0) for i in range(6)]
    targets = [np.array([-1 if r[k] is None else int(r[k] != 0) for r in rows]) for k in range(2)]
    chosen: set[int] = set()
    for y in targets:
        on, off = np.zeros(1 << HASH_BITS), np.zeros(1 << HASH_BITS)
        for g, v in zip(present, y, strict=True):
            if v >= 0:
                (on if v else off)[g] += 1
        gap = np.abs(on / max(1, (y == 1).sum()) - off / max(1, (y == 0).sum()))
        gap[on + off < 5] = 0
        best = np.argsort(-gap, kind="stable")[:FEATURES]
        chosen |= set(best[gap[best] > 0].tolist())
    model = Model(np.array(sorted(chosen), np.int64), edges, np.zeros((len(chosen) + n_bins, 2)), np.zeros(2))
    x = np.zeros((len(rows), len(chosen) + n_bins), np.float32)
    for i, g in enumerate(present):
        hit = model.column[g]
        x[i, hit[hit >= 0]] = 1
        x[i, model.bins(stats[i])] = 1
    for k, y in enumerate(targets):
        known = y >= 0
        if not (y == 1).any() or not (y == 0).any():
            model.bias[k] = 20.0 if (y == 1).any() else -20.0
            continue
        model.bias[k], model.weights[:, k] = logistic(x[known], y[known])
    return model


def logistic(x: np.ndarray, y: np.ndarray, rounds: int = 12) -> tuple[float, np.ndarray]:
    """Ridge logistic regression by Newton steps; the bias is not shrunk."""
    x = np.hstack([np.ones((len(x), 1), np.float32), x]).astype(float)
    ridge = np.r_[1e-6, np.full(x.shape[1] - 1, RIDGE)]
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + np.diag(ridge), x.T @ (y - p) - ridge * w)
        w += step
        if np.abs(step).max() < 1e-6:
            break
    return float(w[0]), w[1:]


def fitted(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, sample: int = SAMPLE) -> Model:
    """The model of at most ``sample`` labelled documents, those whose ids have the least hashes (one text of each id)."""
    prepare(docs.sparkSession)
    some = labels.where("label_id is not null").orderBy(F.xxhash64("label_id"), "label_id", "low", "toxic").limit(sample)
    rows = docs.select(F.col(id_col).alias("label_id"), F.col(text_col).alias("text")).join(F.broadcast(some), "label_id").groupBy("label_id", "low", "toxic").agg(F.min("text").alias("text")).select("text", "low", "toxic")
    model = fit([tuple(r) for r in rows.mapInArrow(_sample_batches, "low int, toxic int, grams binary, stats array<double>").collect()])
    relieve(docs.sparkSession)  # the sample's rows and the matrices of the fit
    return model


# -- scoring


def _score_batches(model, text_at: int):
    """The columns before the text, and the evidence; the text does not come back."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model.value
        for part in slices(batches, text=text_at):
            odds = np.array([m.evidence(t or "") for t in part.column(text_at).to_pylist()])
            yield pa.RecordBatch.from_arrays([*part.columns[:text_at], pa.array(odds[:, 0]), pa.array(odds[:, 1])], [*part.schema.names[:text_at], "__low", "__toxic"])

    return run


def _sigmoid(x: Column) -> Column:
    return 1 / (1 + F.exp(-x))


def _logit(p: Column) -> Column:
    q = F.greatest(F.lit(1e-9), F.least(F.lit(1 - 1e-9), p))
    return F.log(q / (1 - q))


def path_shifts(outcomes: DataFrame) -> DataFrame:
    """``host, path, n, shift_low, shift_toxic`` from ``host, path, low, toxic`` (outcomes between 0 and 1).

    Grouped sums only; the few global figures are one row; a host with very many paths is spread."""
    paths = written(outcomes.groupBy("host", "path").agg(F.count("*").alias("n"), *(F.sum(k).alias(f"s_{k}") for k in HEADS)), "paths")
    hosts = written(paths.groupBy("host").agg(F.sum("n").alias("n_host"), F.count("*").alias("n_paths"), *(F.sum(f"s_{k}").alias(f"h_{k}") for k in HEADS)), "hosts")
    world = hosts.agg(F.sum("n_host").alias("n"), F.count("*").alias("hosts"), *(F.sum(f"h_{k}").alias(k) for k in HEADS)).first()
    out = spread_join(paths, hosts, ["host"], "n_paths")
    if not world.n:
        return out.select("host", "path", "n", *(F.lit(0.0).alias(f"shift_{k}") for k in HEADS))
    mean = {k: min(1 - 1e-6, max(1e-6, world[k] / world.n)) for k in HEADS}

    def strength(rows: DataFrame, n: str, s: str, around: Column, k: str) -> float:
        """Observations that the level above is worth: the mean's variance over the variance between groups."""
        spread = mean[k] * (1 - mean[k])
        r = rows.agg(F.sum(F.col(n) * F.pow(F.col(s) / F.col(n) - around, 2)).alias("q"), F.count("*").alias("g"), F.sum(n).alias("n"), F.sum(F.col(n).cast("double") * F.col(n)).alias("n2")).first()
        if not r.g or r.g < 2:
            return 1e6
        between = (r.q - (r.g - 1) * spread) / max(1e-9, r.n - r.n2 / r.n)
        return min(1e6, max(1.0, spread / max(1e-9, between) - 1))

    for k in HEADS:
        by_host = strength(hosts, "n_host", f"h_{k}", F.lit(mean[k]), k)
        out = out.withColumn(f"m_{k}", (F.col(f"h_{k}") + by_host * mean[k]) / (F.col("n_host") + by_host))
        by_path = strength(out, "n", f"s_{k}", F.col(f"m_{k}"), k)
        out = out.withColumn(f"shift_{k}", _logit((F.col(f"s_{k}") + by_path * F.col(f"m_{k}")) / (F.col("n") + by_path)) - float(np.log(mean[k] / (1 - mean[k]))))
    return out.select("host", "path", "n", *(f"shift_{k}" for k in HEADS))


def scored(docs: DataFrame, labels: DataFrame, keep: list[str], id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", path_col: str = "lang", sample: int = SAMPLE) -> DataFrame:
    """The columns ``keep`` of each document with ``p_low``, ``p_toxic`` (posteriors) and ``kept``.

    ``labels`` has ``doc_id, quality, toxic``; null marks are unknown, repeated ones count as the worst.  The text is
    scored once and the scores written; only numbers are summed and joined.  Null and empty texts are judged like other
    empty texts, null hosts and paths are groups of their own, rows without an id have no label, repeated rows stay, and
    an empty table gives no rows; without labels all documents are kept.
    """
    prepare(docs.sparkSession)
    marks = labels.groupBy(F.col("doc_id").alias("label_id")).agg((1 - F.min("quality")).cast("int").alias("low"), F.max("toxic").cast("int").alias("toxic"))
    marks = written(marks, "marks")
    model = docs.sparkSession.sparkContext.broadcast(fitted(docs, marks, id_col, text_col, sample))
    carried = list(dict.fromkeys([*keep, id_col]))
    rows = docs.select(*(F.col(c).alias(f"c{i}") for i, c in enumerate(carried)), F.coalesce(F.col(host_col).cast("string"), F.lit("\0")).alias("host"), F.coalesce(F.col(path_col).cast("string"), F.lit("\0")).alias("path"), F.col(text_col).cast("string").alias("text"))
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema[:-1]) + ", __low double, __toxic double"
    done = rows.mapInArrow(_score_batches(model, len(rows.columns) - 1), schema)
    done = written(done, "scores")
    of_id = f"c{carried.index(id_col)}"
    known = done.select(F.col(of_id).alias("label_id"), "host", "path", "__low", "__toxic")
    none = [F.lit(None).cast("int").alias(k) for k in HEADS]
    known = known.where("label_id is not null").join(marks, "label_id", "left").unionByName(known.where("label_id is null").select("*", *none))
    outcomes = known.select("host", "path", *(F.coalesce(F.col(k).cast("double"), _sigmoid(F.col(f"__{k}"))).alias(k) for k in HEADS))
    shifts = written(path_shifts(outcomes), "shifts")
    done = spread_join(done, shifts, ["host", "path"], "n")
    done = done.withColumn("p_low", _sigmoid(F.col("__low") + F.col("shift_low"))).withColumn("p_toxic", _sigmoid(F.col("__toxic") + F.col("shift_toxic")))
    return done.select(*(F.col(f"c{i}").alias(c) for i, c in enumerate(carried) if c in keep), "p_low", "p_toxic", ((F.col("p_low") < REJECT) & (F.col("p_toxic") < REJECT)).alias("kept"))


def accepted(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", path_col: str = "lang", sample: int = SAMPLE) -> DataFrame:
    """The rows of ``docs`` that the classifier keeps, with their columns.  Only numbers of rows are written and joined."""
    columns = docs.columns
    marked = numbered(docs.select(*(F.col(c).alias(f"c{i}") for i, c in enumerate(columns))), docs, "numbered")
    need = {name: f"c{columns.index(c)}" for name, c in (("id_col", id_col), ("text_col", text_col), ("host_col", host_col), ("path_col", path_col))}
    gone = written(scored(marked, labels, ["rid"], **need, sample=sample).where("not kept").select("rid"), "rejected")
    return without(marked, gone).select(*(F.col(f"c{i}").alias(c) for i, c in enumerate(columns)))
