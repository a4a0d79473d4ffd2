"""Quality rules as a bitmask ledger.

``ledger`` measures every text once and evaluates every rule once, storing the
failures as bits beside the measurements. Policies (named, versioned sets of
rules) are then masks over those bits: applying another policy, or asking what a
policy would keep without one of its rules, never touches a text again.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import worker
from .common import free_name

WINDOW = 8
SYMBOLS = "#*$%&|<>"
SPACES = " \t\n\x0b\x0c\r"

MEASURES = (
    "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
    "n_lines", "n_alpha_words", "n_upper_words",
)

#: Bit position = place in this list; only ever append, so stored ledgers stay valid.
#: Each condition is SQL over the measurements (64-bit integers, no rounding) and is
#: true where the text fails the rule.
RULES: tuple[tuple[str, str], ...] = (
    ("few_words", "n_words < 20"),
    ("repeated_windows", "100 * n_repeat_words > 30 * n_words"),
    ("many_symbols", "100 * n_symbols > 30 * n_words"),
    ("duplicate_lines", "100 * n_dup_lines > 30 * n_lines"),
    ("shouting", "100 * n_upper_words > 50 * n_words"),
    ("word_length", "word_chars < 2 * n_words OR word_chars > 15 * n_words"),
    ("few_letters", "100 * n_alpha_words < 60 * n_words"),
    ("very_long", "n_words > 10000000"),
)


@dataclass(frozen=True)
class Policy:
    """Reject on any failed ``hard`` rule, or on more than ``allowed`` failed ``soft`` ones."""

    name: str
    version: int
    hard: tuple[str, ...]
    soft: tuple[str, ...] = ()
    allowed: int = 0

    def mask(self, rules: tuple[str, ...]) -> int:
        bits = {name: 1 << i for i, (name, _) in enumerate(RULES)}
        return sum(bits[r] for r in rules)

    def rejects(self, bits: Column, without: str | None = None) -> Column:
        hard = self.mask(tuple(r for r in self.hard if r != without))
        soft = self.mask(tuple(r for r in self.soft if r != without))
        return (bits.bitwiseAND(F.lit(hard)) != 0) | (F.bit_count(bits.bitwiseAND(F.lit(soft))) > self.allowed)


BASE = ("few_words", "repeated_windows")
POLICIES = (
    Policy("base", 1, BASE),
    Policy("strict", 1, BASE + ("many_symbols", "duplicate_lines", "shouting", "word_length", "few_letters")),
    Policy("web", 1, BASE + ("many_symbols", "shouting"), ("duplicate_lines", "word_length", "few_letters"), 1),
)
PRODUCTION = POLICIES[2]


def repeated_words(ids: np.ndarray) -> int:
    """Words covered by windows of ``WINDOW`` words that occur twice or more."""
    n = len(ids) - WINDOW + 1
    if n < 2:
        return 0
    with np.errstate(over="ignore"):
        key = np.zeros(n, np.uint64)
        for j in range(WINDOW):
            key = key * np.uint64(0x9E3779B97F4A7C15) + ids[j : j + n].astype(np.uint64) + np.uint64(1)
            key ^= key >> np.uint64(29)
    order = np.argsort(key, kind="stable")
    same = key[order[1:]] == key[order[:-1]]
    if not same.any():  # equal windows have equal keys
        return 0
    windows = np.lib.stride_tricks.sliding_window_view(ids, WINDOW)
    if (windows[order[1:][same]] == windows[order[:-1][same]]).all():
        hit = np.zeros(n, bool)
        hit[order[1:][same]] = True
        hit[order[:-1][same]] = True
    else:  # two different windows share a key: compare the windows themselves
        _, back, counts = np.unique(windows, axis=0, return_inverse=True, return_counts=True)
        hit = counts[back.ravel()] > 1
    edge = np.zeros(len(ids) + 1, np.int64)
    edge[:n] += hit
    edge[WINDOW : WINDOW + n] -= hit
    return int((np.cumsum(edge)[:-1] > 0).sum())


def measure(text: str | None) -> tuple[int, ...]:
    """The measurements of one whole text, in the order of ``MEASURES``."""
    if not text:
        return (0,) * len(MEASURES)
    words = text.encode("utf-8", "surrogatepass").split()  # splits bytes at the six ASCII spaces only
    codes: dict[bytes, int] = {}
    ids = np.fromiter([codes.setdefault(w, len(codes)) for w in words], np.int64, len(words))
    counts = np.bincount(ids, minlength=len(codes)) if codes else np.zeros(0, np.int64)
    alpha = np.fromiter([not w.isascii() or any(c.isalpha() for c in w.decode()) for w in codes], bool, len(codes))
    upper = np.fromiter([w.isupper() and len(w) > 1 for w in codes], bool, len(codes))
    seen: set[str] = set()
    dup = lines = 0
    for line in text.split("\n"):
        if line.strip(SPACES):
            lines += 1
            dup += line in seen
            seen.add(line)
    return (
        len(words),
        len(text) - sum(map(text.count, SPACES)),
        sum(map(text.count, SYMBOLS)),
        dup,
        repeated_words(ids),
        lines,
        int(counts[alpha].sum()),
        int(counts[upper].sum()),
    )


def measures(texts: pa.Array) -> pa.Array:
    worker.enter("quality")
    rows = [measure(t.as_py()) for t in texts]
    columns = list(zip(*rows, strict=True)) or [()] * len(MEASURES)
    return pa.StructArray.from_arrays([pa.array(c, pa.int64()) for c in columns], list(MEASURES))


def ledger(df: DataFrame, text: str = "text") -> DataFrame:
    """``df`` with one struct column ``ledger``: ``bits`` and every measurement.

    The text is read once; every other column (whatever its name) passes through,
    rows are neither added nor lost, and repeated rows get equal entries. Null and
    empty texts measure zero and so fail ``few_words``. If ``df`` already has a column
    ``ledger`` the new one is called ``ledger_``. A text is measured in one piece of
    memory in proportion to its own length.
    """
    name, raw = free_name(df, "ledger"), free_name(df, "measured")
    out = df.withColumn(raw, F.arrow_udf(measures, ", ".join(f"{m} long" for m in MEASURES))(F.col(text)))
    value = {m: F.col(f"`{raw}`.{m}") for m in MEASURES}
    bits = F.lit(0).cast("long")
    for i, (_, condition) in enumerate(RULES):
        here = condition
        for m in sorted(MEASURES, key=len, reverse=True):
            here = here.replace(m, f"`{raw}`.`{m}`") if m in here.split() else here
        bits = bits.bitwiseOR(F.when(F.expr(here), F.lit(1 << i).cast("long")).otherwise(F.lit(0).cast("long")))
    return out.withColumn(name, F.struct(bits.alias("bits"), *(value[m].alias(m) for m in MEASURES))).drop(raw)


def apply_policy(entries: DataFrame, policy: Policy = PRODUCTION, bits: str = "ledger.bits") -> DataFrame:
    """``entries`` with a boolean ``kept`` (renamed if taken)."""
    return entries.withColumn(free_name(entries, "kept"), ~policy.rejects(F.col(bits)))


def ablations(entries: DataFrame, policies: tuple[Policy, ...] = POLICIES, bits: str = "ledger.bits") -> DataFrame:
    """What each policy rejects, and what it would reject without each of its rules.

    One aggregation to (bits, count), at most ``2 ** len(RULES)`` rows however large
    the ledger, then bitwise arithmetic on those. Columns: policy, version, without
    (null: the whole policy), rejected, and alone = what only that rule rejects.
    """
    patterns = entries.groupBy(F.col(bits).alias("bits")).agg(F.count("*").alias("n"))
    cases = [
        (p, w, F.sum(F.when(p.rejects(F.col("bits"), w), F.col("n")).otherwise(0)).alias(f"r{k}"))
        for k, (p, w) in enumerate((p, w) for p in policies for w in (None, *p.hard, *p.soft))
    ]
    sums = patterns.agg(*(c for _, _, c in cases))
    whole = {p.name: k for k, (p, w, _) in enumerate(cases) if w is None}
    rows = F.array(
        *(
            F.struct(
                F.lit(p.name).alias("policy"),
                F.lit(p.version).alias("version"),
                F.lit(w).cast("string").alias("without"),
                F.coalesce(F.col(f"r{k}"), F.lit(0)).cast("long").alias("rejected"),
                F.coalesce(F.col(f"r{whole[p.name]}") - F.col(f"r{k}"), F.lit(0)).cast("long").alias("alone"),
            )
            for k, (p, w, _) in enumerate(cases)
        )
    )
    return sums.select(F.explode(rows).alias("r")).select("r.*")
