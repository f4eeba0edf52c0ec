"""Quality rules whose cutoffs carry a proof.

A rule rejects a document whose score is at or above a cutoff. The promise is one for each stratum
(language, and rows without one): with probability 1 - ``delta`` over all strata together, the rules of a
stratum reject at most ``alpha`` of its good documents. It is spent evenly over the rules tested there, the
level over strata and rules (Bonferroni). For each rule the cutoff is chosen on the labelled rows: walking
from the most lenient cutoff down, each one is accepted while an exact binomial test shows that the rule
rejects at most its part of ``alpha`` (fixed-sequence testing: no further correction along the walk).

How many rules a stratum tests follows from its number of good labels alone, before any score is looked
at: as many of ``RULES``, in that order, as could be certified at all if no good document were rejected.
Too few labels for one rule certify nothing, and only the base rule acts there; ``strata_report`` and the
column ``certified`` say where.

Statistics cover whole texts. A null text has no words. An empty table gives no rows; without labels
only the base rule acts; repeated rows are judged one by one; other columns pass unread.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import SPACE, runs_of, saved, text_slices, table, word_codes

STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper")
RULES = ("symbols", "repeats", "dup_lines", "upper", "short")
BINS = 400
#: Share of the good documents of a stratum that all its rules together may reject; chance that this fails anywhere.
ALPHA, DELTA, WINDOW = 0.02, 0.05, 8

_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&|<>")] = True
_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True


def text_stats(texts: list[bytes]) -> dict[str, np.ndarray]:
    """The statistics of each text, exactly (no hashing)."""
    n = len(texts)
    sizes = np.array([len(t) for t in texts], np.int64)
    edge = np.concatenate(([0], np.cumsum(sizes)))
    raw = np.frombuffer(b"".join(texts), np.uint8)

    def per_text(mask: np.ndarray) -> np.ndarray:
        total = np.concatenate(([0], np.cumsum(mask, dtype=np.int64)))
        return total[edge[1:]] - total[edge[:-1]]

    space = SPACE[raw]
    out = {"word_chars": per_text(((raw & 0xC0) != 0x80) & ~space), "n_symbols": per_text(_SYMBOL[raw]), "n_upper": per_text(_UPPER[raw])}
    dup, lines = np.zeros(n, np.int64), np.zeros(n, np.int64)
    for i, t in enumerate(texts):
        if b"\n" in t:
            own = [x for x in t.split(b"\n") if x.strip()]
            lines[i], dup[i] = len(own), len(own) - len(set(own))
        else:
            lines[i] = bool(t.strip())
    codes, offsets, _ = word_codes(texts)
    out |= {"n_words": np.diff(offsets), "n_dup_lines": dup, "n_lines": lines, "n_repeat_words": repeated_words(codes, offsets)}
    return out


def repeated_words(codes: np.ndarray, offsets: np.ndarray, window: int = WINDOW) -> np.ndarray:
    """Words inside windows that occur twice or more in their text; ``window`` is a power of two."""
    total = len(codes)
    if total < window:
        return np.zeros(len(offsets) - 1, np.int64)
    rank, width = codes, 1
    while width < window:  # equal pairs of equal halves
        rank = pd.factorize((rank[: len(rank) - width] << 32) | rank[width:])[0]
        width *= 2
    owner = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    valid = np.flatnonzero(owner[: total - window + 1] == owner[window - 1 :])
    ids, _ = pd.factorize((owner[valid].astype(np.int64) << 32) | rank[valid])
    twice = valid[np.bincount(ids)[ids] > 1] if len(ids) else valid
    change = np.zeros(total + 1, np.int64)
    change[twice] += 1
    np.add.at(change, twice + window, -1)
    covered = np.concatenate(([0], np.cumsum(np.cumsum(change[:-1]) > 0)))
    return covered[offsets[1:]] - covered[offsets[:-1]]


def scores(s: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    """Each rule's score as a bin from 0 to BINS; higher is worse."""
    part = lambda a, b: np.minimum(BINS, BINS * a // np.maximum(b, 1))
    return {
        "symbols": part(s["n_symbols"], s["word_chars"]),
        "repeats": part(s["n_repeat_words"], s["n_words"]),
        "dup_lines": part(s["n_dup_lines"], s["n_lines"]),
        "upper": part(s["n_upper"], s["word_chars"]),
        "short": np.maximum(0, BINS - s["n_words"]),
    }


def base_failed(s: dict[str, np.ndarray]) -> np.ndarray:
    return (s["n_words"] < 20) | (100 * s["n_repeat_words"] > 30 * s["n_words"])


_SCORED = "doc_id long, lang string, " + ", ".join(f"{c} long" for c in STATS) + ", base_failed boolean, " + ", ".join(f"s_{r} int" for r in RULES)


def _score_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for a, b, texts in text_slices(batch):
            s = text_stats(texts)
            cols = [batch.column("doc_id")[a:b], batch.column("lang")[a:b]] + [pa.array(s[c].astype(np.int64)) for c in STATS]
            cols += [pa.array(base_failed(s))] + [pa.array(v.astype(np.int32)) for v in scores(s).values()]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "lang", *STATS, "base_failed", *[f"s_{r}" for r in RULES]])


def scored(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long"), F.col("lang").cast("string"), "text").mapInArrow(_score_batches, _SCORED)


def binomial_cdf(k: int, n: int, p: float) -> float:
    """P(X <= k) of a binomial, summed in log space."""
    if k >= n:
        return 1.0
    at = lambda i: math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(p) + (n - i) * math.log1p(-p)
    return min(1.0, math.fsum(math.exp(at(i)) for i in range(k + 1)))


def walk(good: np.ndarray, bad: np.ndarray, alpha: float, level: float) -> int | None:
    """Cutoff bin from label counts by bin: of the certified ones the most lenient that rejects the most bad rows."""
    n, best, most, false, caught = int(good.sum()), None, 0, 0, 0
    for t in range(len(good) - 1, 0, -1):  # bin 0 is the best score and never a cutoff
        false, caught = false + int(good[t]), caught + int(bad[t])
        if binomial_cdf(false, n, alpha) > level:
            break
        if caught > most:
            best, most = t, caught
    return best


def testable(n: int, strata: int, alpha: float, delta: float) -> int:
    """How many rules ``n`` good labels can certify, each for an even part of ``alpha`` and of the level."""
    fits = [j for j in range(1, len(RULES) + 1) if n * math.log1p(-alpha / j) <= math.log(delta / (max(1, strata) * j))]
    return max(fits, default=0)


def _counts(rows: DataFrame, labels: DataFrame) -> dict[str | None, dict[str, np.ndarray]]:
    """{stratum: {rule: (good, bad) by bin}}; only counts by stratum, rule and bin reach the driver."""
    marks = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.min("quality").alias("quality"))
    held = rows.where("not base_failed").join(marks, "doc_id")
    long = held.select("lang", "quality", F.explode(F.array(*[F.struct(F.lit(r).alias("rule"), F.col(f"s_{r}").alias("bin")) for r in RULES])).alias("x"))
    counts = long.groupBy("lang", "x.rule", "x.bin").agg(F.sum(F.when(F.col("quality") == 1, 1).otherwise(0)).alias("good"), F.sum(F.when(F.col("quality") == 0, 1).otherwise(0)).alias("bad")).collect()
    out: dict[str | None, dict[str, np.ndarray]] = {}
    for lang, rule, at, good, bad in counts:
        out.setdefault(lang, {}).setdefault(rule, np.zeros((2, BINS + 1), np.int64))[:, at] += (good, bad)
    return out


def certified_cutoffs(rows: DataFrame, labels: DataFrame, alpha: float = ALPHA, delta: float = DELTA) -> dict[str | None, dict[str, int]]:
    """{stratum: {rule: cutoff}} from the labelled rows. A stratum whose rules may be tested is there even if none found a cutoff."""
    held = _counts(rows, labels)
    out: dict[str | None, dict[str, int]] = {}
    for lang, by_rule in held.items():
        tested = testable(int(next(iter(by_rule.values()))[0].sum()), len(held), alpha, delta)
        if tested:
            found = {rule: walk(*by_rule[rule], alpha / tested, delta / (len(held) * tested)) for rule in RULES[:tested]}
            out[lang] = {rule: t for rule, t in found.items() if t is not None}
    return out


def strata_report(docs: DataFrame, labels: DataFrame, alpha: float = ALPHA, delta: float = DELTA) -> DataFrame:
    """(lang, n_good, n_rules tested, rule, cutoff bin) of each stratum with labels; rule and cutoff are null where none is certified."""
    rows = saved(scored(docs))
    held, cutoffs = _counts(rows, labels), certified_cutoffs(rows, labels, alpha, delta)
    out = []
    for lang, by_rule in held.items():
        n = int(next(iter(by_rule.values()))[0].sum())
        out += [(lang, n, testable(n, len(held), alpha, delta), rule, t) for rule, t in (cutoffs.get(lang) or {None: None}).items()]
    return docs.sparkSession.createDataFrame(out, "lang string, n_good long, n_rules int, rule string, cutoff int")


def verdict(cutoffs: dict[str | None, dict[str, int]], of: str = ""):
    """Column: true unless the base rule or a certified one rejects."""
    failed = F.col(f"{of}base_failed")
    for lang, rules in cutoffs.items():
        for rule, t in rules.items():
            failed = failed | (F.col(f"{of}lang").eqNullSafe(F.lit(lang).cast("string")) & (F.col(f"{of}s_{rule}") >= t))
    return ~failed


def quality_report(docs: DataFrame, labels: DataFrame) -> DataFrame:
    rows = saved(scored(docs))
    cutoffs = certified_cutoffs(rows, labels)
    certified = F.lit(False)
    for lang in cutoffs:
        certified = certified | F.col("lang").eqNullSafe(F.lit(lang).cast("string"))
    return rows.select("doc_id", *STATS[:5], "base_failed", verdict(cutoffs).alias("kept"), "lang", certified.alias("certified"))


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs`` that pass, unchanged. Scores are written beside the text once: no join, no shuffle of texts."""
    beside = next(f"scores{i or ''}" for i in range(len(docs.columns) + 1) if f"scores{i or ''}" not in [c.lower() for c in docs.columns])
    fields = [f.split() for f in _SCORED.split(", ")]

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, texts in text_slices(batch):
                s, part = text_stats(texts), batch.slice(a, b - a)
                values = [part.column("doc_id").cast(pa.int64()), part.column("lang").cast(pa.string())] + [pa.array(s[c].astype(np.int64)) for c in STATS]
                values += [pa.array(base_failed(s))] + [pa.array(v.astype(np.int32)) for v in scores(s).values()]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.StructArray.from_arrays(values, names=[n for n, _ in fields])], names=[*batch.schema.names, beside])

    both = T.StructType([*docs.schema.fields, T.StructField(beside, T.StructType.fromDDL(_SCORED))])
    rows = saved(docs.mapInArrow(score, both))
    cutoffs = certified_cutoffs(rows.select(f"{beside}.*"), labels)
    return rows.where(verdict(cutoffs, f"{beside}.")).select(*[F.col(f"`{c}`") for c in docs.columns])


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
