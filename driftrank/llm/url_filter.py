"""URL filter: rules by host and path, and a ratio of two character models for what no rule settles.

Two smoothed variable-order Markov models are learnt from the URLs that the rules accept and reject. A URL's score is
the log-likelihood difference per character; the threshold is calibrated on ruled URLs that the models have not learnt
from (those whose hash falls into one of FOLDS folds; equal URLs fall into one fold).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from driftrank.llm import words as W

RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))
ORDER, CELLS, PRIOR, FOLDS = 4, 1 << 19, 3.0, 5
BINS, SPREAD = 2001, 4.0  # histogram of scores from -SPREAD to SPREAD for the threshold


def parts(url: str = "url") -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path columns; both empty for null or without '://'."""
    u = F.coalesce(url, F.lit(""))
    at = F.locate("://", u)
    rest = F.when(at > 0, F.substring(u, at + 3, F.length(u))).otherwise("")
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    # translate lower-cases A-Z alone; lower() would change other letters too
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def rule_of(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest rule that fits and its verdict, or null."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for what, rule in sorted(rules, key=lambda r: (len(r[1]), r[1])):
        h, _, p = rule.partition("/")
        fits = ((host == h) | host.endswith("." + h)) & path.startswith("/" + p)
        name, verdict = F.when(fits, rule).otherwise(name), F.when(fits, what).otherwise(verdict)
    return name, verdict


def _contexts(texts: pa.Array) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """Per order 0..ORDER the hashed cells of (context, character); those of contexts; row offsets. An end mark closes a row."""
    values = [(t or "") + "\x03" for t in W.strings(texts)]
    size = np.fromiter(map(len, values), np.int64, len(values))
    starts = np.concatenate(([0], np.cumsum(size)))
    x = np.frombuffer("".join(values).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    depth = np.arange(len(x)) - np.repeat(starts[:-1], size)
    h = np.zeros(len(x), np.uint64)
    pair, ctx = [], []
    for k in range(ORDER + 1):
        if k:
            prev = np.zeros(len(x), np.uint64)
            prev[k:] = x[:-k] if k else x
            prev[depth < k] = np.uint64(0x1FFFFF)  # before the row
            h = W.mix(h * np.uint64(31) + prev + np.uint64(k))
        ctx.append((W.mix(h + np.uint64(k + 77)) % np.uint64(CELLS)).astype(np.int64))
        pair.append((W.mix(h ^ W.mix(x + np.uint64(1009 * (k + 1)))) % np.uint64(CELLS)).astype(np.int64))
    return list(zip(pair, ctx, strict=True)), starts, size


def learn(urls: DataFrame) -> np.ndarray:
    """Counts of both classes from (text, label) rows: 4 blocks of CELLS (pairs and contexts of label 0, then of 1)."""

    def fill(mine, b):
        label = b.column(b.schema.get_field_index("label")).to_numpy(zero_copy_only=False)
        cells, _, size = _contexts(b.column(b.schema.get_field_index("text")))
        who = np.repeat(label, size).astype(np.int64)
        for pair, ctx in cells:
            mine += np.bincount(np.concatenate((who * 2 * CELLS + pair, who * 2 * CELLS + CELLS + ctx)), minlength=4 * CELLS)

    return W.summed_sketch(urls.select("text", F.col("label").cast("int").alias("label")), 4 * CELLS, fill)


def ratios(texts: pa.Array, counts: np.ndarray) -> np.ndarray:
    """Per text: (log P(text | accepted) - log P(text | rejected)) / characters, both models with back-off by order."""
    cells, starts, size = _contexts(texts)
    logs = []
    for label in (0, 1):
        pair, ctx = counts[label * 2 * CELLS : label * 2 * CELLS + CELLS], counts[label * 2 * CELLS + CELLS : (label + 1) * 2 * CELLS]
        p = np.full(int(starts[-1]), 1 / 256)
        for a, b in cells:
            p = (pair[a] + PRIOR * p) / (np.maximum(ctx[b], pair[a]) + PRIOR)
        logs.append(np.add.reduceat(np.log(p), starts[:-1]) if len(p) else np.zeros(0))
    return (logs[1] - logs[0]) / np.maximum(size, 1)


def _scored(frame: DataFrame, counts) -> DataFrame:
    names = frame.columns

    def run(batches):
        for b in W.slices(batches, "text"):
            s = ratios(b.column(b.schema.get_field_index("text")), counts.value)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(s)], [*b.schema.names, "ratio"])

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in frame.schema.fields)
    return frame.mapInArrow(run, f"{schema}, ratio double").select(*names, "ratio")


def filter_urls(pages: DataFrame, id_col: str = "page_id", rules=RULES) -> DataFrame:
    """(id, host, path, rule, ratio, verdict) of each row; a verdict is the rule's, or the models'.

    Null urls and urls without '://' have empty host and path and no rule. The models read whole urls, null ones as empty
    texts. With no held-out ruled URL of one kind the threshold is 0. Repeated rows each get a row.
    """
    host, path = parts()
    base = pages.select(F.col(id_col).alias("k"), host.alias("host"), path.alias("path"), F.coalesce("url", F.lit("")).alias("text"))
    name, verdict = rule_of(F.col("host"), F.col("path"), rules)
    base = base.withColumns({"rule": name, "said": verdict})
    ruled = base.where("said is not null").select("text", F.when(F.col("said") == "allow", 1).otherwise(0).alias("label"))
    fold = F.pmod(F.xxhash64("text"), F.lit(FOLDS))
    counts = pages.sparkSession.sparkContext.broadcast(learn(ruled.where(fold != 0)))
    step = F.floor((F.greatest(F.lit(-SPREAD), F.least(F.lit(SPREAD), F.col("ratio"))) + SPREAD) / (2 * SPREAD) * (BINS - 1)).cast("int")
    hist = np.zeros((BINS, 2))
    for r in _scored(ruled.where(fold == 0), counts).groupBy(step.alias("bin"), "label").count().collect():  # 2 * BINS rows at most
        hist[r["bin"], r["label"]] = r["count"]
    tail = hist[::-1].cumsum(axis=0)[::-1] / np.maximum(hist.sum(axis=0), 1)
    gain = tail[:, 1] - tail[:, 0]
    best = np.flatnonzero(gain >= gain.max() - 1e-12)
    cut = float((best[len(best) // 2] / (BINS - 1)) * 2 * SPREAD - SPREAD) if hist.sum(axis=0).min() > 0 else 0.0
    scored = _scored(base, counts)
    own = F.when(F.col("ratio") >= cut, "allow").otherwise("block")
    return scored.select(F.col("k").alias(id_col), "host", "path", "rule", "ratio", F.coalesce("said", own).alias("verdict"))


def op5_url_filter(spark, sf_dir) -> DataFrame:
    return filter_urls(W.docs(spark, sf_dir, "pages"))
