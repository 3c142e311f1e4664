"""Windows over the sentences of a document: packing, the two schedules, training samples.

Everything stands twice: in plain Python for loops that depend on a model's answers, and as a
Column for decisions known in advance. The Columns fold over a document's own arrays, so windows
of billions of documents need no shuffle.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

#: One of the 512 places of a sequence belongs to the leading marker.
MAX_TOKENS, MAX_SENTENCES = 511, 60
WIN = "array<struct<first:int,last:int>>"


def fit_last(n_tok: list[int], first: int, limit: int = MAX_TOKENS, cap: int = MAX_SENTENCES) -> int:
    """Last sentence of the window from ``first``; a sentence beyond the limit makes a window alone."""
    last, size = first, n_tok[first]
    while last + 1 < len(n_tok) and size + n_tok[last + 1] <= limit and last + 2 - first <= cap:
        last += 1
        size += n_tok[last]
    return last


@dataclass(frozen=True)
class Fixed:
    """The next window begins ``step`` - 1 sentences before the last one: a constant overlap."""

    step: int = 5

    def next_start(self, first: int, last: int, positives, n: int) -> int:
        return max(last - self.step + 1, first + 1)


@dataclass(frozen=True)
class Adaptive:
    """The next window begins after the latest positive among the last sentences of this one, else on its last.

    ``lookback`` counts moves back from the last sentence ('moves'), or sentences ('count').
    Only decisions of this window count.
    """

    lookback: int = 10
    span: str = "moves"

    def next_start(self, first: int, last: int, positives, n: int) -> int:
        low = max(first, last - self.lookback + (self.span == "count"))
        found = [i for i in range(low, last + 1) if positives(i)]
        return max(found[-1] + 1 if found else last, first + 1)


def trace(n_tok: list[int], positive, policy, limit: int = MAX_TOKENS, cap: int = MAX_SENTENCES) -> list[tuple[int, int]]:
    """All windows of one document; positive: sentence index to decision."""
    out, first, n = [], 0, len(n_tok)
    while first < n:
        last = fit_last(n_tok, first, limit, cap)
        out.append((first, last))
        if last >= n - 1:
            break
        first = policy.next_start(first, last, positive, n)
    return out


def _let(value: Column, body) -> Column:
    return F.transform(F.array(value), body)[0]


def prefix_sums(n_tok: Column) -> Column:
    """0 and the running totals."""
    start = F.array(F.lit(0))
    return F.aggregate(n_tok, start, lambda acc, x: F.concat(acc, F.array(F.element_at(acc, -1) + x)))


def window_array(n_tok: Column, positive: Column, policy, limit: int = MAX_TOKENS, cap: int = MAX_SENTENCES) -> Column:
    """Column twin of ``trace``: token counts and decisions, both arrays, to the array of windows.

    The fold makes one step for each sentence and stops changing once the document is covered.
    """

    def body(known: Column) -> Column:
        toks, decided, n = known["toks"], known["decided"], known["n"]

        def step(s: Column, _: Column) -> Column:
            first = s["first"]
            fits = lambda a, x: F.struct((a["size"] + x).alias("size"), (a["k"] + (a["size"] + x <= limit).cast("int")).alias("k"))
            reach = F.aggregate(F.slice(toks, first + 1, cap), F.struct(F.lit(0).alias("size"), F.lit(0).alias("k")), fits, lambda a: a["k"])
            last = first + F.greatest(reach, F.lit(1)) - 1

            def close(last: Column) -> Column:
                if isinstance(policy, Fixed):
                    start = last - policy.step + 1
                else:
                    low = F.greatest(first, last - policy.lookback + (1 if policy.span == "count" else 0))
                    start = F.coalesce(F.array_max(F.filter(F.sequence(low, last), lambda i: F.get(decided, i))) + 1, last)
                return F.struct(F.when(last >= n - 1, n).otherwise(F.greatest(start, first + 1)).cast("int").alias("first"), F.concat(s["wins"], F.array(F.struct(first.cast("int").alias("first"), last.cast("int").alias("last")))).alias("wins"))

            return F.when(first >= n, s).otherwise(_let(last, close))

        zero = F.struct(F.lit(0).cast("int").alias("first"), F.array().cast(WIN).alias("wins"))
        return F.aggregate(F.when(n > 0, F.sequence(F.lit(1), n)).otherwise(F.array().cast("array<int>")), zero, step, lambda s: s["wins"])

    # all inputs are bound once: the optimizer must not write them out inside the fold
    return _let(F.struct(n_tok.alias("toks"), positive.alias("decided"), F.size(n_tok).alias("n")), body)


def forward_windows(n_sent: Column, step: int = 10, cap: int = MAX_SENTENCES) -> Column:
    """Training windows by a fixed forward step: starts 0, step, 2 step, ...; short last ones stay."""
    starts = F.when(n_sent > 0, F.sequence(F.lit(0), n_sent - 1, F.lit(step))).otherwise(F.array().cast("array<int>"))
    return F.transform(starts, lambda s: F.struct(s.cast("int").alias("first"), (F.least(s + cap, n_sent) - 1).cast("int").alias("last")))


def reference_windows(n_tok: Column, ends_para: Column, lookback: int = 10, limit: int = MAX_TOKENS, cap: int = MAX_SENTENCES) -> Column:
    """Training windows by the adaptive schedule, with the references for decisions."""
    return window_array(n_tok, ends_para, Adaptive(lookback), limit, cap)


def cut(n_tok: Column, limit: int = MAX_TOKENS, keep_partial: bool = False) -> Column:
    """Over-long sample, first version: everything beyond the limit goes.

    Whole sentences only (one at least); with ``keep_partial`` the next sentence fills what is left.
    """

    def body(prefix: Column) -> Column:
        whole = F.greatest(F.size(F.filter(prefix, lambda p: p <= limit)) - 1, F.lit(1))
        kept = F.transform(F.slice(n_tok, 1, whole), lambda x: F.least(x, F.lit(limit)))
        room = F.lit(limit) - F.get(prefix, whole)
        part = (whole < F.size(n_tok)) & (room > 0)
        return F.concat(kept, F.when(part, F.array(room.cast("int"))).otherwise(F.array().cast("array<int>"))) if keep_partial else kept

    return _let(prefix_sums(n_tok), body)


def trim(n_tok: Column, limit: int = MAX_TOKENS) -> Column:
    """Over-long sample, second version: all sentences stay, the long ones are shortened to a common cap.

    The cap is the largest with a total within the limit; what is left over goes one token each to
    the earliest sentences above the cap.
    """
    total = F.aggregate(n_tok, F.lit(0), lambda a, x: a + x)

    def fits(m: Column) -> Column:
        return F.aggregate(n_tok, F.lit(0), lambda a, x: a + F.least(x, m)) <= limit

    def raised(bit: int):
        return lambda m: F.when((m + bit <= limit) & fits(m + bit), m + bit).otherwise(m)

    # the cap by bisection: ten halvings are enough for limits to 1023
    low = F.lit(1)
    for bit in (512, 256, 128, 64, 32, 16, 8, 4, 2, 1):
        low = _let(low, raised(bit))

    def spread(m: Column) -> Column:
        left = F.greatest(F.lit(limit) - F.aggregate(n_tok, F.lit(0), lambda a, x: a + F.least(x, m)), F.lit(0))
        over = F.filter(F.transform(n_tok, lambda x, i: F.when(x > m, i)), lambda i: i.isNotNull())
        lucky = F.slice(over, 1, left)
        return F.transform(n_tok, lambda x, i: F.least(x, m) + F.when(F.array_contains(lucky, i), 1).otherwise(0))

    return F.when(total <= limit, n_tok).otherwise(_let(low, spread))


def trim_list(n_tok: list[int], limit: int = MAX_TOKENS) -> list[int]:
    if sum(n_tok) <= limit:
        return list(n_tok)
    m = max([c for c in range(1, limit + 1) if sum(min(x, c) for x in n_tok) <= limit], default=1)
    left = max(0, limit - sum(min(x, m) for x in n_tok))
    out = []
    for x in n_tok:
        extra = x > m and left > 0
        left -= extra
        out.append(min(x, m) + extra)
    return out


def cut_list(n_tok: list[int], limit: int = MAX_TOKENS) -> list[int]:
    out, size = [], 0
    for x in n_tok:
        if out and size + x > limit:
            break
        out.append(min(x, limit))
        size += x
    return out
