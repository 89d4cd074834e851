"""Quality rules with host-level verdicts.

Every document is held against a few rules. The failures of a host's documents are summed; a beta prior, fitted to the
hosts' failure rates by the method of moments, shrinks each rate towards the corpus rate, so a host with few documents
is not judged by them alone. The verdicts go back to the documents. Base rules hold everywhere. How far the other (soft)
rules hold is the host's verdict: on a trusted host, whose rate is below TRUSTED_RATE with the certainty of TRUST_SD
standard deviations, failing one is forgiven as the host's style; on a rejected host, whose shrunk rate is above
HOST_LIMIT, they hold at half their limits; on any other host they hold as they are. A document that passes the strict
rules stays wherever it is.

Only counts per host are shuffled (partial aggregates first), so a host with a third of all rows costs no more than
another. Verdicts are one row per host; the stage that carries texts joins only hosts that are trusted or rejected, by
broadcast up to BROADCAST_HOSTS of them.

Defined results: null or empty text has zero words and fails the base rules; a null host is a host of its own; repeated
rows count as often as they occur; a very long text is one slice of its own in a worker, in memory of a few times its
length; other columns, whatever their names, pass through unread; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textkit
from .scratch import cut

_TEXT, _HOST = "__text__", "__host__"
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
#: Soft rules: symbols per hundred words, mean word length in characters, repeated lines.
MAX_SYMBOL_PERCENT = 10
MEAN_WORD_CHARS = (2, 15)
MAX_DUP_LINES = 3
HOST_LIMIT = 0.5
TRUSTED_RATE = 0.05
TRUST_SD = 1.645
BROADCAST_HOSTS = 1_000_000


def repeated(keys: np.ndarray, owners: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Flags over elements: its (owner, key) occurs twice or more; it is not the first of them."""
    order = np.lexsort((keys, owners))
    k, o = keys[order], owners[order]
    same = np.zeros(len(k) + 1, bool)
    same[1:-1] = (k[1:] == k[:-1]) & (o[1:] == o[:-1])
    twice, later = np.zeros(len(k), bool), np.zeros(len(k), bool)
    twice[order] = same[1:] | same[:-1]
    later[order] = same[:-1]  # lexsort is stable, so the first of equal elements comes first
    return twice, later


def repeat_words(ids: np.ndarray, bounds: np.ndarray, size: int, vocabulary: int) -> np.ndarray:
    """Flags over words: inside a window of ``size`` words that its text holds twice or more."""
    n, docs = len(ids), textkit.owner(bounds)
    if n < size:
        return np.zeros(n, bool)
    key = ids[: n - size + 1].copy()
    for j in range(1, size):
        if key.size and int(key.max()) > (1 << 62) // max(vocabulary, 1):
            key = np.unique(key, return_inverse=True)[1].astype(np.int64)
        key = key * vocabulary + ids[j : n - size + 1 + j]
    inside = docs[: n - size + 1] == docs[size - 1 :]
    twice, _ = repeated(key[inside], docs[: n - size + 1][inside])
    start = np.zeros(n + 1, np.int32)
    at = np.flatnonzero(inside)[twice]
    start[at] += 1
    np.add.at(start, at + size, -1)
    return np.cumsum(start[:n]) > 0


def duplicate_lines(texts: pa.Array) -> np.ndarray:
    """Per text the lines (split at \\n) with a word that equal an earlier line."""
    lists = pc.split_pattern(texts.cast(pa.large_string()).fill_null(""), "\n")
    flat = lists.flatten()
    docs = np.repeat(np.arange(len(lists)), pc.list_value_length(lists).to_numpy(zero_copy_only=False))
    ids, values = textkit.codes(flat)
    worded = pc.match_substring_regex(values, r"[^\x20\x09-\x0D]").to_numpy(zero_copy_only=False)[ids]
    _, later = repeated(ids[worded], docs[worded])
    return np.bincount(docs[worded][later], minlength=len(lists))


def rule_counts(texts: pa.Array) -> dict[str, np.ndarray]:
    """The base counts of each text, exact."""
    raw, off = textkit.string_buffers(texts)
    flat, bounds = textkit.words(raw, off)
    ids, values = textkit.codes(flat)
    chars = pc.utf8_length(values).to_numpy(zero_copy_only=False)[ids] if len(ids) else ids
    docs = textkit.owner(bounds)
    n = len(texts)
    symbols = np.isin(raw, np.frombuffer(b"#*$%&|<>", np.uint8))
    upto = np.concatenate([[0], np.cumsum(symbols)])
    return {
        "n_words": np.diff(bounds),
        "word_chars": np.bincount(docs, weights=chars, minlength=n).astype(np.int64),
        "n_symbols": upto[off[1:]] - upto[off[:-1]],
        "n_dup_lines": duplicate_lines(texts),
        "n_repeat_words": np.bincount(docs, weights=repeat_words(ids, bounds, 3, len(values)), minlength=n).astype(np.int64),
    }


def counted(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """The columns ``keep`` of ``docs`` and the base counts (long)."""
    picked = docs.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{text}`").alias(_TEXT))
    schema = T.StructType(picked.schema.fields[:-1] + [T.StructField(c, T.LongType()) for c in COUNTS])

    @textkit.giving_back
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in textkit.slices(batches, _TEXT, textkit.SMALL_SLICE):
            got = rule_counts(b.column(b.num_columns - 1))
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], *[pa.array(got[c].astype(np.int64)) for c in COUNTS]], names=[*b.schema.names[:-1], *COUNTS])

    return picked.mapInArrow(run, schema)


def counted_rows(docs: DataFrame, text: str, host: str) -> DataFrame:
    """``row`` (a struct of all columns), ``host`` and the base counts; the text travels once."""
    rows = docs.select(F.struct(*[F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(docs.columns)]).alias("row"))
    at_text, at_host = docs.columns.index(text), docs.columns.index(host)
    schema = T.StructType([*rows.schema.fields, T.StructField("host", docs.schema[host].dataType), *[T.StructField(c, T.LongType()) for c in COUNTS]])

    @textkit.giving_back
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            column = whole.column(0)
            flat = pa.RecordBatch.from_arrays([column, column.field(at_host), column.field(at_text)], names=["row", "host", _TEXT])
            for b in textkit.slices(iter([flat]), _TEXT, textkit.SMALL_SLICE):
                got = rule_counts(b.column(2))
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *[pa.array(got[c].astype(np.int64)) for c in COUNTS]], names=["row", "host", *COUNTS])

    return rows.mapInArrow(run, schema)


def verdicts(hosts: DataFrame, limit: float = HOST_LIMIT, trusted: float = TRUSTED_RATE) -> DataFrame:
    """(host, n, failed) to (host, host_rate, host_rejected, host_trusted): rates shrunk by a beta prior of the hosts' mean and variance."""
    rate = F.col("failed") / F.col("n")
    prior = hosts.agg(F.avg(rate).alias("m"), F.coalesce(F.var_samp(rate), F.lit(0.0)).alias("v"))
    # Strength of the prior, a + b; equal rates on all hosts mean the strongest prior.
    strength = F.when(F.col("v") <= 0, 1e6).otherwise(F.greatest(F.lit(1.0), F.col("m") * (1 - F.col("m")) / F.col("v") - 1))
    prior = prior.select(F.coalesce("m", F.lit(0.0)).alias("m"), F.coalesce(strength, F.lit(1e6)).alias("strength"))
    shrunk = (F.col("failed") + F.col("m") * F.col("strength")) / (F.col("n") + F.col("strength"))
    sd = F.sqrt(shrunk * (1 - shrunk) / (F.col("n") + F.col("strength") + 1))
    rated = hosts.crossJoin(F.broadcast(prior))  # one row of prior
    return rated.select("host", shrunk.alias("host_rate"), (shrunk > limit).alias("host_rejected"), (shrunk + TRUST_SD * sd < trusted).alias("host_trusted"))


def with_rules(c: DataFrame) -> DataFrame:
    """The counts with base_failed, rule_failed (base or soft) and strict_failed (base or a soft rule at half its limit)."""
    base = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))

    def soft(share: float) -> Column:
        low, high = MEAN_WORD_CHARS
        symbols = 100 * F.col("n_symbols") > MAX_SYMBOL_PERCENT * share * F.col("n_words")
        # Half the room on either side of the middle.
        middle, room = (low + high) / 2, (high - low) / 2 * share
        length = ~F.col("word_chars").between((middle - room) * F.col("n_words"), (middle + room) * F.col("n_words"))
        return symbols | length | (F.col("n_dup_lines") > MAX_DUP_LINES * share)

    return c.withColumn("base_failed", base).withColumn("rule_failed", base | soft(1.0)).withColumn("strict_failed", base | soft(0.5))


def _verdict(rejected: Column, trusted: Column) -> Column:
    """Whether a document stays, by its rules and its host's verdict."""
    return ~F.col("base_failed") & F.when(rejected, ~F.col("strict_failed")).when(trusted, True).otherwise(~F.col("rule_failed"))


def _hosts(ruled: DataFrame, host: str) -> DataFrame:
    return ruled.groupBy(F.col(host).alias("host")).agg(F.count("*").alias("n"), F.count_if("rule_failed").alias("failed"))


def judged(docs: DataFrame, text: str = "text", host: str = "source", keep: tuple[str, ...] = ("doc_id",), limit: float = HOST_LIMIT, trusted: float = TRUSTED_RATE) -> DataFrame:
    """``keep``, the base counts, base_failed, rule_failed (any rule), strict_failed, host_rate, host_rejected, host_trusted and
    kept, a row per row of ``docs``. Names in ``keep`` other than these are free."""
    source = docs.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{host}`").alias(_HOST), F.col(f"`{text}`").alias(_TEXT))
    c = with_rules(cut(counted(source, _TEXT, (*keep, _HOST))))
    rated = verdicts(_hosts(c, _HOST), limit, trusted).withColumnRenamed("host", "__of__")
    return c.join(rated, F.col(_HOST).eqNullSafe(F.col("__of__"))).withColumn("kept", _verdict(F.col("host_rejected"), F.col("host_trusted"))).drop(_HOST, "__of__")


def kept_documents(docs: DataFrame, text: str = "text", host: str = "source", limit: float = HOST_LIMIT, trusted: float = TRUSTED_RATE) -> DataFrame:
    """``docs`` without the rejected rows, columns unchanged, whatever their names.

    The counts are made twice, once for the hosts' rates and once beside the text, so that no text is shuffled or kept.
    """
    own = docs.select(F.col(f"`{host}`").alias("host"), F.col(f"`{text}`").alias(_TEXT))
    rated = verdicts(_hosts(with_rules(counted(own, _TEXT, ("host",))), "host"), limit, trusted)
    special = cut(rated.where("host_rejected OR host_trusted").select(F.col("host").alias("of"), "host_rejected", "host_trusted"))
    if special.count() <= BROADCAST_HOSTS:
        special = F.broadcast(special)
    marked = with_rules(counted_rows(docs, text, host)).where("NOT base_failed")
    joined = marked.join(special, F.col("host").eqNullSafe(F.col("of")), "left")
    stays = joined.where(_verdict(F.coalesce("host_rejected", F.lit(False)), F.coalesce("host_trusted", F.lit(False))))
    return stays.select(*[F.col(f"row.c{k}").alias(c) for k, c in enumerate(docs.columns)])
