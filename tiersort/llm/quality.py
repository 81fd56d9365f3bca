"""Quality classifier with hierarchical empirical Bayes.

Document evidence: a logistic regression over measures of the text's surface
for quality, and one over telling words and beginnings of words for toxicity, both
fitted on at most ``most_labels`` labelled documents (chosen by a hash of
their id, a bounded sample; everything else covers all documents).

Site evidence, for quality and for toxicity alike: the documents' probabilities
are averaged by grouped aggregation for each host and each path of a host. A
host's mean is shrunk towards the global one, a path's towards its host's, with
weights estimated from the spread between groups (a beta-binomial fit by
moments), so that sparse sites say little. The posterior log odds of a document
are its own plus what the others of its site add over the global prior.

Null and empty texts have neutral evidence except for their missing words and
are rejected. A null host or path is a group of its own. Repeated rows count
each and are judged alike. Labels of unknown documents, with nulls, or of
repeated ids are ignored but for the smallest row of an id. Without usable
labels of both classes nothing is rejected but wordless texts. An empty table
gives no row.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tiersort.llm.common import shipped, staged

MOST_LABELS = 12_000
MEASURES = 16


def stems(word: str) -> set[str]:
    """A word and its beginnings of 4 to 7 letters."""
    return {word, *(word[:k] for k in range(4, min(8, len(word))))}


def measures(text: str | None) -> tuple[np.ndarray, Counter]:
    """Surface measures of a text, and its words in lower case with their counts."""
    text = text or ""
    words = text.split()
    n, size = len(words), max(1, len(text))
    if not n:
        return np.zeros(MEASURES), Counter()
    low = text.lower().split()
    counts = Counter(low)
    bare: Counter = Counter()
    for w, k in counts.items():
        bare[w.strip(".,;:!?\"'()[]|#$%&*")] += k
    pairs = len(set(zip(low, low[1:]))) / max(1, n - 1)
    lines = [x for x in text.split("\n") if x.strip()]
    upper = sum(1 for w in words if len(w) > 1 and w.isupper())
    odd = text.count("#") + text.count("$") + text.count("%") + text.count("&") + text.count("*")
    return np.array([
        1.0, np.log(n), size / n / 8, upper / n, text.count("!") / n, text.count("|") / n, odd / n, (text.count(".") + text.count(",")) / n,
        len(counts) / n ** 0.8, pairs, max(counts.values()) / n, len(set(lines)) / max(1, len(lines)), np.log1p(n / max(1, len(lines))),
        (text.count("http") + text.count("@")) / n, sum(map(text.count, "0123456789")) / size, sum(w[-1].isalnum() for w in words) / n,
    ]), bare


class Model:
    """Weights for quality (surface) and for toxicity (telling beginnings of words)."""

    def __init__(self, quality: np.ndarray | None, mean: np.ndarray, scale: np.ndarray, telling: list[str], toxic: np.ndarray | None):
        self.quality, self.mean, self.scale, self.telling, self.toxic = quality, mean, scale, telling, toxic
        self.slot = {w: i for i, w in enumerate(telling)}

    def evidence(self, text: str | None) -> tuple[float, float]:
        """Log odds of good quality and of toxicity."""
        x, words = measures(text)
        if not x[0]:
            return -20.0, -20.0
        good = 20.0 if self.quality is None else float(np.clip(((x - self.mean) / self.scale) @ self.quality, -20, 20))
        bad = -20.0 if self.toxic is None else float(np.clip(told(self.hits(words), words.total()) @ self.toxic, -20, 20))
        return good, bad

    def hits(self, words: Counter) -> np.ndarray:
        out, slot = np.zeros(len(self.slot)), self.slot
        for w, k in words.items():
            for s in {w, w[:4], w[:5], w[:6], w[:7]}:
                if s in slot:
                    out[slot[s]] += k
        return out


def told(hits: np.ndarray, n: float) -> np.ndarray:
    """Features of toxicity: bounded counts, bounded rates, length."""
    return np.concatenate([[1.0, np.log(max(1, n)) / 5], np.minimum(hits, 4), np.minimum(100 * hits / max(1, n), 4)])


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, steps: int = 30) -> np.ndarray:
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) + ridge * w
        h = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w))
        step = np.linalg.solve(h, g)
        w -= step * min(1.0, 5 / max(1e-9, np.abs(step).max()))
    return w


def sample(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, most_labels: int) -> DataFrame:
    """At most ``most_labels`` rows (id, text, quality, toxic); of several texts with one id the smallest."""
    first = labels.where(F.col(id_col).isNotNull() & F.col("quality").isNotNull() & F.col("toxic").isNotNull()).groupBy(id_col).agg(
        F.min(F.struct("quality", "toxic")).alias("l")).select(F.col(id_col).alias("_id"), "l.quality", "l.toxic")
    few = first.orderBy(F.xxhash64("_id"), "_id").limit(most_labels)
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    found = texts.join(F.broadcast(few), F.col("id") == F.col("_id")).select("id", "text", "quality", "toxic")
    return found.groupBy("id").agg(F.min(F.struct("text", "quality", "toxic")).alias("l")).select("id", "l.*")


def fit(rows: DataFrame, least: int = 4, most_telling: int = 120) -> Model:
    """Model of a bounded set of rows (id, text, quality, toxic).

    Measures come to the driver (at most ``most_labels`` short vectors).
    Beginnings of words are counted by documents where they are; of those that
    part toxic documents from others most (likelihood ratio), the best come.
    """
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [measures(t.as_py()) for t in b.column(0)]
            all_stems = [sorted(set().union(*map(stems, w))) if w else [] for _, w in got]
            yield pa.RecordBatch.from_arrays([pa.array([m.tolist() for m, _ in got], pa.list_(pa.float64())), pa.array(all_stems, pa.list_(pa.string())),
                                              b.column(1), b.column(2)], names=["m", "stems", "quality", "toxic"])

    kept = staged(rows.select("text", F.col("quality").cast("int"), F.col("toxic").cast("int")), "sample")
    seen = staged(kept.mapInArrow(run, "m array<double>, stems array<string>, quality int, toxic int"), "labelled")
    head = seen.select("m", "quality", "toxic").collect()
    y = np.array([r.quality for r in head], float)
    x = np.array([r.m for r in head]).reshape(len(head), MEASURES)
    mean, scale = (x.mean(0), x.std(0) + 1e-6) if len(x) else (np.zeros(MEASURES), np.ones(MEASURES))
    mean[0], scale[0] = 0.0, 1.0
    model = Model(logistic((x - mean) / scale, y) if len(set(y)) > 1 else None, mean, scale, [], None)
    bad = sum(r.toxic for r in head)
    fine = len(head) - bad
    if not bad or not fine:
        return model
    t, n = F.col("t") + 0.0, F.col("n") + 0.0
    part = lambda k, of: k * F.log((k + 0.01) / of / (n / (bad + fine)))
    ratio = part(t, bad) + part(n - t, fine)
    ranked = (seen.select(F.explode("stems").alias("w"), "toxic").groupBy("w").agg(F.count("*").alias("n"), F.sum("toxic").alias("t")).where(F.col("t") >= least)
              .where(t / bad > 3 * (n - t) / fine).withColumn("g", ratio).orderBy(F.desc("g"), F.length("w"), "w").limit(8 * most_telling).collect())
    telling: list[str] = []
    near: dict[str, tuple[int, int]] = {}
    for r in ranked:  # of nested beginnings in about the same documents the first stays
        if not any(q != r.w and (q.startswith(r.w) or r.w.startswith(q)) and abs(near[q][0] - r.n) <= 0.2 * r.n for q in telling):
            telling.append(r.w)
            near[r.w] = (r.n, r.t)
        if len(telling) == most_telling:
            break
    draft = Model(model.quality, mean, scale, telling, None)
    sent = shipped(rows.sparkSession, draft)

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = sent()
        for b in batches:
            out = []
            for v in b.column(0):
                words = measures(v.as_py())[1]
                out.append(told(held.hits(words), words.total()).tolist())
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.list_(pa.float64())), b.column(1)], names=["x", "toxic"])

    got = kept.select("text", "toxic").mapInArrow(features, "x array<double>, toxic int").toArrow()  # as many rows as the sample
    z = np.array(got.column(1).to_pylist(), float)
    v = got.column(0).combine_chunks().flatten().to_numpy().reshape(len(z), -1)
    draft.toxic = logistic(v, z, ridge=0.3)
    return draft


def scores(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", path_col: str = "lang") -> DataFrame:
    """Rows (id, host, path, good, bad): the document's own log odds."""
    sent = shipped(docs.sparkSession, model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent()
        for b in batches:
            got = [m.evidence(t.as_py()) for t in b.column(3)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array([g for g, _ in got], pa.float64()), pa.array([x for _, x in got], pa.float64())],
                                             names=["id", "host", "path", "good", "bad"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, F.col(host_col).cast("string").alias("_host"), F.col(path_col).cast("string").alias("_path"), text_col).mapInArrow(
        run, f"id {kind}, host string, path string, good double, bad double")


def _weight(mean: str, n: str) -> Column:
    """Beta-binomial strength by moments: how many documents the prior is worth."""
    m, v = F.avg(mean), F.var_pop(mean)
    inside = F.avg(F.col(mean) * (1 - F.col(mean)) / F.col(n))
    between = F.greatest(v - inside, F.lit(1e-4))
    return F.least(F.greatest(m * (1 - m) / between - 1, F.lit(1.0)), F.lit(1000.0))


def site_sums(scored: DataFrame) -> DataFrame:
    """Rows (host, path, with the sums of both probabilities and the numbers of documents of path and host).

    Probabilities are summed as millionths, so the order of rows doesn't matter.
    """
    p = lambda x: F.round(1e6 / (1 + F.exp(-F.col(x)))).cast("long")
    paths = scored.groupBy("host", "path").agg(F.sum(p("good")).alias("path_good"), F.sum(p("bad")).alias("path_bad"), F.count("*").alias("path_n"))
    hosts = paths.groupBy("host").agg(F.sum("path_good").alias("host_good"), F.sum("path_bad").alias("host_bad"), F.sum("path_n").alias("host_n"))
    return paths.join(hosts.withColumnRenamed("host", "_h"), F.col("host").eqNullSafe(F.col("_h"))).drop("_h")


def strengths(sums: DataFrame) -> DataFrame:
    """One row: the global means, and how many documents the priors of hosts and paths are worth."""
    hosts = sums.groupBy("host").agg(*[F.first(c).alias(c) for c in ("host_good", "host_bad", "host_n")])
    mean = lambda c, n: F.col(c) / F.col(n) / 1e6
    at_hosts = hosts.select("*", mean("host_good", "host_n").alias("g"), mean("host_bad", "host_n").alias("b")).agg(
        (F.sum("host_good") / F.sum("host_n") / 1e6).alias("all_good"), (F.sum("host_bad") / F.sum("host_n") / 1e6).alias("all_bad"),
        _weight("g", "host_n").alias("host_w_good"), _weight("b", "host_n").alias("host_w_bad"))
    at_paths = sums.select("*", mean("path_good", "path_n").alias("g"), mean("path_bad", "path_n").alias("b")).agg(
        _weight("g", "path_n").alias("path_w_good"), _weight("b", "path_n").alias("path_w_bad"))
    return at_hosts.crossJoin(F.broadcast(at_paths))  # one row each


def _odds(x: Column) -> Column:
    x = F.least(F.greatest(x, F.lit(1e-3)), F.lit(1 - 1e-3))
    return F.log(x / (1 - x))


def _posterior(kind: str, own: Column, one: Column) -> Column:
    """A path's mean shrunk to its host's, that to the global one; ``own`` (in millionths) of ``one`` document is left out."""
    host = ((F.col(f"host_{kind}") - own) / 1e6 + F.col(f"host_w_{kind}") * F.col(f"all_{kind}")) / (F.col("host_n") - one + F.col(f"host_w_{kind}"))
    return ((F.col(f"path_{kind}") - own) / 1e6 + F.col(f"path_w_{kind}") * host) / (F.col("path_n") - one + F.col(f"path_w_{kind}"))


def judge(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", path_col: str = "lang",
          most_labels: int = MOST_LABELS, least_quality: float = 0.5, most_toxic: float = 0.5, row_col: str | None = None) -> DataFrame:
    """Rows (id, quality, toxicity, site_quality, site_toxicity, keep), one for each document row.

    ``row_col`` is what the rows are to be named by, if not by the id of the labels.
    """
    model = fit(sample(docs, labels, id_col, text_col, most_labels))
    return combined(staged(scores(docs, model, row_col or id_col, text_col, host_col, path_col), "scored"), least_quality, most_toxic)


def combined(scored: DataFrame, least_quality: float = 0.5, most_toxic: float = 0.5) -> DataFrame:
    """Rows (id, host, path, good, bad) with their sites' evidence.

    A document's posterior log odds are its own and what the others of its
    site add over the global mean.
    """
    sums = staged(site_sums(scored), "sites")
    t = scored.join(sums.withColumnsRenamed({"host": "_h", "path": "_p"}), F.col("host").eqNullSafe(F.col("_h")) & F.col("path").eqNullSafe(F.col("_p")))
    t = t.crossJoin(F.broadcast(strengths(sums)))  # one row
    out = {}
    for kind in ("good", "bad"):
        own = F.round(1e6 / (1 + F.exp(-F.col(kind)))).cast("long")
        lift = _odds(_posterior(kind, own, F.lit(1))) - _odds(F.col(f"all_{kind}"))
        out[kind] = F.round(1 / (1 + F.exp(-(F.col(kind) + lift))), 6)
    site = {kind: F.round(_posterior(kind, F.lit(0), F.lit(0)), 6) for kind in out}
    return t.select("id", out["good"].alias("quality"), out["bad"].alias("toxicity"), site["good"].alias("site_quality"), site["bad"].alias("site_toxicity")).withColumn(
        "keep", (F.col("quality") >= least_quality) & (F.col("toxicity") < most_toxic))
