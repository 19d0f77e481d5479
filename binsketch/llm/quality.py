"""Quality classifier: a document's own evidence, and what its site is worth.

Two linear classifiers (good quality, toxic) are fitted on a bounded sample of
labelled documents. Over all documents their probabilities are summed by host
and by path; each host is shrunk toward the global rate and each path toward
its host, the more the fewer documents it has (Beta priors whose strength comes
from the spread between groups). A document's verdict adds its own log-odds to
the shift of its path.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import claim, free_name, map_batches, texts_of, written

BUCKETS, RESERVED = 1 << 18, 64  # hashed words; places below 64 are for shapes
MOST_ENTRIES, MOST_CHARS, SAMPLE = 150_000, 64, 20_000
UNITS = re.compile(r"\w+|[^\w\s]+")
HEADS = ("quality", "toxic")
CAPITALS, SIGNS = 0, 1  # marks of a chunk
LEAST_CHI, LEAST_DOCS = 25.0, 5


class Featurizer:
    """Which features a text has: its words and runs of signs (hashed), shares of capitals, signs and repeats, length."""

    def __init__(self):
        self.memo: dict[str, bytes] = {}

    def chunk(self, chunk: str) -> bytes:
        import xxhash

        units = UNITS.findall(chunk)
        found = [RESERVED + xxhash.xxh64_intdigest(u.lower()) % (BUCKETS - RESERVED) for u in units]
        if len(chunk) > 1 and chunk.isupper():
            found.append(CAPITALS)
        if any(len(u) > 1 and not u[0].isalnum() or u == "|" for u in units):
            found.append(SIGNS)
        out = np.array(found, np.uint32).tobytes()
        if len(chunk) <= MOST_CHARS:
            if len(self.memo) >= MOST_ENTRIES:
                self.memo.clear()
            self.memo[chunk] = out
        return out

    def features(self, text: str) -> np.ndarray:
        claim("quality", self.memo.clear)
        chunks = text.split(" ")
        memo, chunk = self.memo, self.chunk
        ids, times = np.unique(np.frombuffer(b"".join([memo.get(c) or chunk(c) for c in chunks]), np.uint32), return_counts=True)
        count = {int(i): int(n) for i, n in zip(ids[:2], times[:2], strict=True) if i <= SIGNS}
        share = lambda n, of, steps: min(steps, steps * n // max(of, 1))
        words = ids[ids > SIGNS]
        shapes = 2 + share(count.get(CAPITALS, 0), len(chunks), 10), 13 + share(len(words), int(times.sum()) - sum(count.values()), 15), 29 + min(len(text).bit_length(), 20), 50 + share(count.get(SIGNS, 0), len(chunks), 10)
        return np.concatenate([np.array(shapes, np.uint32), words])


_featurizer = Featurizer()


def telling(rows: list[np.ndarray], labels: np.ndarray) -> np.ndarray:
    """Which features go with the label: in LEAST_DOCS documents or more, and a chi-square that chance doesn't reach among all of them."""
    of = lambda label: np.bincount(np.concatenate([r for r, y in zip(rows, labels, strict=True) if y == label]), minlength=BUCKETS).astype(float)
    a, b, n, ones = of(1), of(0), len(labels), labels.sum()
    c, d = ones - a, n - ones - b
    chi = n * np.maximum(np.abs(a * d - b * c) - n / 2, 0) ** 2 / np.maximum((a + b) * (c + d) * ones * (n - ones), 1e-9)
    return (chi >= LEAST_CHI) & (a + b >= LEAST_DOCS)


def fit(rows: list[np.ndarray], labels: np.ndarray, rounds: int = 400, rate: float = 0.5, decay: float = 1e-4) -> np.ndarray:
    """Weights (the last is the intercept) of a logistic regression on telling features; steps are scaled for each weight."""
    w = np.zeros(BUCKETS + 1)
    if not len(rows) or labels.min() == labels.max():
        w[-1] = 0.0 if not len(rows) else 8.0 if labels[0] else -8.0
        return w
    keep = telling(rows, labels)
    number = np.cumsum(keep) - 1
    few = [number[r[keep[r]]] for r in rows]
    doc, index = np.repeat(np.arange(len(rows)), [len(f) for f in few]), np.concatenate(few)
    used, n = np.flatnonzero(keep), len(rows)
    v, bias, seen, seen_bias = np.zeros(len(used)), 0.0, np.full(len(used), 1e-8), 1e-8
    for _ in range(rounds):
        z = np.bincount(doc, v[index], n) + bias
        off = 1 / (1 + np.exp(-np.clip(z, -30, 30))) - labels
        g = np.bincount(index, off[doc], len(used)) + decay * v
        seen += g * g
        v -= rate * g / np.sqrt(seen)
        seen_bias += off.sum() ** 2
        bias -= rate * off.sum() / np.sqrt(seen_bias)
    w[used], w[-1] = v, bias
    return w


def evidence(w: np.ndarray, features: np.ndarray) -> float:
    return float(w[features].sum() + w[-1])


@dataclass
class Model:
    weights: np.ndarray  # one row for each head


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> Model:
    """Fit both heads on at most ``sample`` labelled rows, chosen by a hash of the id (the bound on what reaches the driver).

    Rows with a null label don't count for that head. Without labels all evidence is 0.
    """
    chosen = labels.select(F.col(id_col).alias("label_id"), *HEADS).filter("label_id is not null").orderBy(F.xxhash64("label_id"), *HEADS).limit(sample)
    joined = docs.select(F.col(id_col).alias("own_id"), F.col(text_col).alias("text")).join(F.broadcast(chosen), F.col("own_id") == F.col("label_id"))

    def run(batch):
        yield {"features": [_featurizer.features(t).tobytes() for t in texts_of(batch)]} | {h: batch.column(h) for h in HEADS}

    rows = map_batches(joined.select("text", *(F.col(h).cast("int").alias(h) for h in HEADS)), run, "features binary, quality int, toxic int").collect()
    rows = sorted(((np.frombuffer(r.features, np.uint32), *(r[h] for h in HEADS)) for r in rows), key=lambda r: r[0].tobytes())
    found = []
    for k in range(1, len(HEADS) + 1):
        own = [r for r in rows if r[k] is not None]
        found.append(fit([r[0] for r in own], np.array([r[k] for r in own], float)))
    return Model(np.array(found))


def scored(docs: DataFrame, model: Model, keep: list[str], text_col: str = "text") -> DataFrame:
    """``keep`` columns of docs, with quality_evidence and toxic_evidence (log-odds); an exchange-free pass."""
    shared = docs.sparkSession.sparkContext.broadcast(model.weights.astype(np.float32))
    kinds = dict(docs.dtypes)

    def run(batch):
        found = []
        for t in texts_of(batch, text_col):
            f = _featurizer.features(t)
            found.append([evidence(w, f) for w in shared.value])
        a = np.array(found).reshape(-1, 2)
        yield {c: batch.column(c) for c in keep} | {"quality_evidence": a[:, 0], "toxic_evidence": a[:, 1]}

    return map_batches(docs.select(*dict.fromkeys([*keep, text_col])), run, ", ".join(f"`{c}` {kinds[c]}" for c in keep) + ", quality_evidence double, toxic_evidence double")


def sigmoid(x: Column) -> Column:
    return 1 / (1 + F.exp(-x))


def logit(p: Column) -> Column:
    q = F.least(F.greatest(p, F.lit(1e-4)), F.lit(1 - 1e-4))
    return F.log(q / (1 - q))


def site_shifts(evidence_rows: DataFrame, host: str, path: str) -> DataFrame:
    """host, path, n, and for each head the path's shift: log-odds of its posterior rate less those of the global rate.

    Sums by path, then by host, then all: each from the one before, so a host with
    a third of all rows is a handful of partial sums. The strength of a prior is
    mean * (1 - mean) / spread - 1 (moments), between 1 and 10,000.
    """
    sums = [F.sum(sigmoid(F.col(f"{h}_evidence"))).alias(h) for h in HEADS]
    paths = written(evidence_rows.groupBy(F.coalesce(host, F.lit("")).alias("host"), F.coalesce(path, F.lit("")).alias("path")).agg(F.count(F.lit(1)).alias("n"), *sums), "paths")
    hosts = paths.groupBy("host").agg(F.sum("n").alias("host_n"), *(F.sum(h).alias(f"host_{h}") for h in HEADS))
    # one row of global rates and of the spread between hosts and between paths
    total = paths.agg(F.sum("n").alias("n"), *(F.sum(h).alias(h) for h in HEADS)).first()
    n = total["n"] or 0
    out = paths.join(hosts, "host")
    for h in HEADS:
        mean = (total[h] or 0.0) / n if n else 0.5
        strong = [_strength(mean, df.agg((F.sum(F.col(c) * F.pow(F.col(s) / F.col(c) - mean, 2)) / F.sum(c)).alias("v")).first().v) for df, c, s in ((hosts, "host_n", f"host_{h}"), (paths, "n", h))]
        of_host = (F.col(f"host_{h}") + strong[0] * mean) / (F.col("host_n") + strong[0])
        of_path = (F.col(h) + strong[1] * of_host) / (F.col("n") + strong[1])
        out = out.withColumn(f"{h}_shift", logit(of_path) - logit(F.lit(mean)))
    return written(out.select("host", "path", "n", *(f"{h}_shift" for h in HEADS)), "site-shifts")


def _strength(mean: float, spread: float | None) -> float:
    return float(np.clip(mean * (1 - mean) / max(spread or 0.0, 1e-9) - 1, 1.0, 10_000.0))


def sites(docs: DataFrame, url_col: str, host: str = "host", path: str = "path", depth: int = 1) -> DataFrame:
    """docs with the host of a url (lower case, without user, port and leading www.) and its first ``depth`` path segments; no url: empty ones."""
    url = F.coalesce(F.col(f"`{url_col}`"), F.lit(""))
    rest = F.regexp_extract(url, r"^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(.*)$", 1)
    name = F.regexp_replace(F.lower(F.regexp_extract(rest, r"^(?:[^/?#@]*@)?([^/?#:]*)", 1)), r"^www\.", "")
    return docs.withColumns({host: name, path: F.regexp_extract(rest, rf"^[^/?#]*((?:/[^/?#]+){{0,{depth}}})", 1)})


def judged(rows: DataFrame, shifts: DataFrame, host: str, path: str, least_quality: float = 0.5, most_toxic: float = 0.5) -> DataFrame:
    """rows with p_quality, p_toxic and keep (p_quality >= least_quality and p_toxic < most_toxic); a site without a row has no shift."""
    names = {c: free_name(c, rows.columns) for c in ("host", "path", *(f"{h}_shift" for h in HEADS))}
    s = shifts.select(*(F.col(c).alias(n) for c, n in names.items()))
    j = rows.join(s, (F.coalesce(F.col(host), F.lit("")) == F.col(names["host"])) & (F.coalesce(F.col(path), F.lit("")) == F.col(names["path"])), "left")
    for h in HEADS:
        j = j.withColumn(f"p_{h}", sigmoid(F.col(f"{h}_evidence") + F.coalesce(names[f"{h}_shift"], F.lit(0.0))))
    return j.withColumn("keep", (F.col("p_quality") >= least_quality) & (F.col("p_toxic") < most_toxic)).drop(*names.values())


VERDICT = ("quality_evidence", "toxic_evidence", "p_quality", "p_toxic", "keep")


def classified(docs: DataFrame, labels: DataFrame, keep: list[str], host: str = "source", path: str = "lang", sample: int = SAMPLE) -> DataFrame:
    """``keep`` columns of every row of docs with its evidence, posteriors and ``keep``.

    Texts are read for training (labelled rows of the sample) and once for the
    evidence, which is written with the kept columns; sites and verdicts come from
    that table. Null or empty texts have shape features only; a null host or path is
    the empty one; repeated rows stay; an empty table gives no rows. Any names may be
    kept: where one is also the name of a verdict's column, the latter is preceded by
    underscores.
    """
    model = train(docs, labels, sample)
    inner = {f"c{i}": c for i, c in enumerate(keep)}
    own = docs.select(*(F.col(f"`{c}`").alias(i) for i, c in inner.items()), F.col(f"`{host}`").alias("host"), F.col(f"`{path}`").alias("path"), *([] if "text" in keep else [F.col("text").alias("text")]))
    text = next((i for i, c in inner.items() if c == "text"), "text")
    rows = written(scored(own, model, [*inner, "host", "path"], text), "evidence")
    done = judged(rows, site_shifts(rows, "host", "path"), "host", "path")
    return done.select(*(F.col(i).alias(c) for i, c in inner.items()), *(F.col(c).alias(free_name(c, keep)) for c in VERDICT))


def accepted(docs: DataFrame, labels: DataFrame, **named) -> DataFrame:
    """The rows of docs that the classifier keeps, in the same columns."""
    rows = classified(docs, labels, docs.columns, **named)
    return rows.filter(F.col(free_name("keep", docs.columns))).select(*(F.col(f"`{c}`") for c in docs.columns))
