"""Operator 4, quality rules by weak supervision.

Rules vote good, vote bad or abstain on each document.  Expectation-maximisation over the counts of
vote patterns (at most 2^rules rows, whatever the corpus) estimates how often each rule votes on good
documents and on each kind of bad ones; a document's verdict is the posterior probability of its pattern, so one
weak vote does not reject a document, as it would if all rules had to pass.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import materialise
from .words import blocks

WINDOW = 8
SYMBOLS = b"#*$%&|<>"
MIN_WORDS = 20
LONG = 20_000
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_letters", "n_bangs", "n_same_next", "n_distinct")
ITERATIONS = 200
PRIOR_DOCUMENTS = 20.0
MAX_FALSE_ALARM = 0.02
#: Least share of its own kind that a rule votes bad on: a kind of bad texts is what its rule sees.
MIN_SEEN = 0.99
#: A document is kept from this posterior probability of good quality on.
KEEP = 0.5

_UPPER, _LOWER = np.arange(65, 91), np.arange(97, 123)
_MULTIPLIERS = np.cumprod(np.full(WINDOW, 0x9E3779B97F4A7C15, "uint64"), dtype="uint64")


def document_counts(raw: bytes) -> tuple[int, ...]:
    """The counts of one text (UTF-8), in the order of :data:`COUNTS`."""
    words = raw.split()
    n = len(words)
    if not n:
        return (0,) * len(COUNTS)
    by_byte = np.bincount(np.frombuffer(raw, "uint8"), minlength=256)
    points = len(raw) - int(by_byte[128:192].sum())
    white = int(by_byte[9:14].sum()) + int(by_byte[32])
    lines = [x for x in raw.split(b"\n") if x.strip()]
    ids = np.fromiter(map(hash, words), "int64", n).view("uint64")
    same = int((ids[1:] == ids[:-1]).sum())
    repeated = 0
    if n > WINDOW:
        windows = np.zeros(n - WINDOW + 1, "uint64")
        for j in range(WINDOW):
            windows += ids[j : n - WINDOW + 1 + j] * _MULTIPLIERS[j]
        ordered = np.sort(windows)
        twice = np.unique(ordered[1:][ordered[1:] == ordered[:-1]])
        if twice.size:
            at = np.flatnonzero(np.isin(windows, twice))
            edge = np.zeros(n + 1, "int64")
            np.add.at(edge, at, 1)
            np.add.at(edge, at + WINDOW, -1)
            repeated = int((np.cumsum(edge[:-1]) > 0).sum())
    upper = int(by_byte[_UPPER].sum())
    return (
        n, points - white, int(by_byte[np.frombuffer(SYMBOLS, "uint8")].sum()), len(lines) - len(set(lines)), repeated,
        len(lines), upper, upper + int(by_byte[_LOWER].sum()), int(by_byte[33]), same, len(set(words)),
    )


def counts(docs: DataFrame, carry: bool = False) -> DataFrame:
    """doc_id and :data:`COUNTS` of every row; with ``carry`` all columns of ``docs`` in a struct __row besides.

    Each column goes to Python once: a second copy of the texts would double an executor's Arrow buffers.
    """
    columns = docs.columns if carry else ["doc_id", "text"]
    kept = docs.select(*[F.col(f"`{c}`") for c in columns])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            rows = [document_counts(t or b"") for t in batch.column("text").cast(pa.binary()).to_pylist()]
            arrays = [pa.array(c, pa.int64()) for c in zip(*rows, strict=True)]
            extra = [pa.StructArray.from_arrays(batch.columns, fields=[*batch.schema])] if carry else []
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *extra, *arrays], ["doc_id", *["__row"] * carry, *COUNTS])

    schema = T.StructType().add("doc_id", "long")
    for name, kind in [("__row", kept.schema)] * carry + [(c, "long") for c in COUNTS]:
        schema = schema.add(name, kind)
    return kept.mapInArrow(run, schema)


def _ratio(a: str, b: str) -> Column:
    return F.coalesce(F.try_divide(F.col(a).cast("double"), F.col(b)), F.lit(0.0))


def _measures() -> dict[str, tuple[Column, float, float]]:
    """Each measure with the mark above which a text looks bad and the one below which it looks good."""
    return {
        "symbols": (_ratio("n_symbols", "n_words"), 0.3, 0.1),
        "capitals": (_ratio("n_upper", "n_letters"), 0.5, 0.2),
        "exclamations": (_ratio("n_bangs", "n_words"), 0.3, 0.1),
        "repeated_passages": (_ratio("n_repeat_words", "n_words"), 0.3, 0.1),
        "repeated_lines": (_ratio("n_dup_lines", "n_lines"), 0.5, 0.1),
        "stuttering": (_ratio("n_same_next", "n_words"), 0.2, 0.05),
    }


def votes() -> dict[str, Column]:
    """0 bad, 1 abstain, 2 good, for each rule.  A rule votes for one side only, or abstains."""
    measures = _measures()
    bad = {k: m > hi for k, (m, hi, _) in measures.items()}
    length, variety = _ratio("word_chars", "n_words"), _ratio("n_distinct", "n_words")
    bad["word_length"] = (length < 2) | (length > 20)
    # a vocabulary grows slower than its text, so from LONG words on the mark falls with the root of the length
    bad["variety"] = (F.col("n_words") >= MIN_WORDS) & (variety < 0.1 * F.sqrt(F.lit(float(LONG)) / F.greatest("n_words", F.lit(LONG))))
    calm = lambda *names: reduce(lambda a, b: a & b, [measures[n][0] < measures[n][2] for n in names])
    good = {"plain": calm("symbols", "capitals", "exclamations") & length.between(3, 14), "fresh": calm("repeated_passages", "repeated_lines", "stuttering")}
    some = F.col("n_words") > 0
    out = {k: F.when(some & c, F.lit(0)).otherwise(F.lit(1)) for k, c in bad.items()}
    return out | {k: F.when(some & c, F.lit(2)).otherwise(F.lit(1)) for k, c in good.items()}


def fit(patterns: np.ndarray, weights: np.ndarray, iterations: int = ITERATIONS) -> dict:
    """EM for a mixture of good documents and one kind of bad ones for each rule that votes bad.

    ``patterns`` has a row for each distinct pattern of votes (0 bad, 1 abstain, 2 good) and
    ``weights`` its number of documents.  Rules cast their votes independently within a kind.  Bad
    texts are bad in different ways, so each rule anchors a kind of its own; kinds may share rules.
    Priors worth ``PRIOR_DOCUMENTS`` documents start from rules that are mostly right.  A rule votes
    bad on at most ``MAX_FALSE_ALARM`` of the good documents, which fixes which kind is good, and on
    ``MIN_SEEN`` of its own kind at least, so a text that no rule votes against is hardly of any bad one.
    Returns posterior (of good), prior, and cast: the share of votes by kind (row 0 good) and rule.
    """
    bad_rules = np.flatnonzero((patterns == 0).any(axis=0))
    votes_cast = (patterns != 1).astype(float)
    kinds, rules = 1 + bad_rules.size, patterns.shape[1]
    good_rules = (patterns == 2).any(axis=0)  # a rule that always abstains speaks for no kind
    start = np.where(good_rules, 0.3, 0.05) * np.ones((kinds, rules))
    start[0] = np.where(good_rules, 0.95, 0.005)
    start[np.arange(1, kinds), bad_rules] = 0.9
    cast, share = start.copy(), np.array([0.9, *[0.1 / max(1, kinds - 1)] * (kinds - 1)]) if kinds > 1 else np.ones(1)
    w, before = weights.astype(float), -np.inf
    for _ in range(iterations):
        cast[0, bad_rules] = np.minimum(cast[0, bad_rules], MAX_FALSE_ALARM)
        cast[np.arange(1, kinds), bad_rules] = np.maximum(cast[np.arange(1, kinds), bad_rules], MIN_SEEN)
        joint = np.log(share) + votes_cast @ np.log(cast).T + (1 - votes_cast) @ np.log1p(-cast).T
        top = joint.max(axis=1, keepdims=True)
        evidence = np.exp(joint - top)
        post = evidence / evidence.sum(axis=1, keepdims=True)
        mass = w @ post
        share = (mass + 1) / (w.sum() + kinds)
        cast = (((w[:, None] * post).T @ votes_cast) + PRIOR_DOCUMENTS * start) / (mass + PRIOR_DOCUMENTS)[:, None]
        cast = np.clip(cast, 1e-6, 1 - 1e-6)
        likelihood = float(w @ (top[:, 0] + np.log(evidence.sum(axis=1))))
        if abs(likelihood - before) < 1e-9 * max(1.0, abs(likelihood)):
            break
        before = likelihood
    return {"posterior": post[:, 0], "prior": float(share[0]), "cast": cast}


def verdicts(counted: DataFrame) -> DataFrame:
    """(__pattern, quality): the posterior of each pattern of votes that occurs in a table with :data:`COUNTS`."""
    # one row for each pattern of votes: at most 2 ** len(rules) = 1024 rows, as a rule votes for one side only
    seen = counted.select(_pattern()).groupBy("__pattern").count().collect()
    numbers = np.array([r["__pattern"] for r in seen], "int64")
    patterns = numbers[:, None] // 3 ** np.arange(len(votes())) % 3
    quality = fit(patterns, np.array([r["count"] for r in seen]))["posterior"] if seen else np.array([])
    return counted.sparkSession.createDataFrame([(int(a), float(b)) for a, b in zip(numbers, quality, strict=True)], "__pattern int, quality double")


def _pattern() -> Column:
    return sum((v * F.lit(3**k) for k, v in enumerate(votes().values())), F.lit(0)).alias("__pattern")


def with_verdict(counted: DataFrame, table: DataFrame) -> DataFrame:
    """Adds quality (posterior), base_failed and kept to a table with :data:`COUNTS`; ``table`` is that of :func:`verdicts`."""
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    return counted.withColumn("__pattern", _pattern()).join(F.broadcast(table), "__pattern").drop("__pattern").withColumn("base_failed", failed).withColumn("kept", ~failed & (F.col("quality") >= KEEP))


def judged(docs: DataFrame) -> DataFrame:
    """One row per input row: doc_id, the counts, quality, base_failed and kept.

    A null or empty text has no words and fails the base rules.  Repeated rows are judged each and
    alike, and so are rows with a null doc_id; an empty table gives an empty result; further columns
    are ignored.
    """
    counted = materialise(counts(docs), "counts")
    return with_verdict(counted, verdicts(counted))


def accepted(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that are kept, with their own columns.

    The texts are counted twice, once for the votes and once for the verdicts, so that they are
    neither shuffled nor written to scratch.
    """
    return with_verdict(counts(docs, carry=True), verdicts(counts(docs))).where("kept").select("__row.*")
