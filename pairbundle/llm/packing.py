"""Best-fit packing of token sequences by a configuration linear program.

Documents become pieces of at most ``capacity`` ids. Only the histogram of piece lengths, at most ``capacity`` numbers, reaches the
driver. There, multiplicative weights solve the covering program over bin patterns to a stated gap: weights are dual prices of the
lengths, a knapsack dynamic program prices patterns, and the prices of a used pattern's lengths fall. The fractional solution covers
every length; its patterns are rounded to whole multiplicities, and best fit completes the plan with what is left. Pieces then find
their places by arithmetic: the rank of a piece among those of its length selects a pattern, a copy of it and an offset.

Null texts count as empty: such a document is its end id alone. Repeated rows are packed each. An empty table gives an empty table. A
text of any length is cut into full pieces and one last piece; nothing else is cut.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pairbundle.llm.common import doc_text, documents, staged
from pairbundle.llm.tokens import encoder, text_batches, tokenizer_path


def pieces(docs: DataFrame, capacity: int = 4096, vocabulary: str | None = None, end_id: int = 1) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every piece of every document, and salt, a number that spreads equal rows."""
    vocabulary = vocabulary or tokenizer_path("word_bpe_49k.json")

    def run(batches):
        made = 0
        for batch in batches:
            doc_ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for a, b in text_batches(texts):
                ids, n = encoder(vocabulary).encode(texts[a:b])
                ids = np.insert(ids, np.cumsum(n), end_id).astype("<u4").tobytes()
                rows: tuple = ([], [], [], [], [], [])
                at = 0
                for doc_id, size in zip(doc_ids[a:b], (n + 1).tolist()):
                    for k, start in enumerate(range(0, size, capacity)):
                        length = min(capacity, size - start)
                        data = ids[4 * (at + start) : 4 * (at + start + length)]
                        made += 1
                        for column, value in zip(rows, (doc_id, k, start, length, zlib.crc32(data), made)):
                            column.append(value)
                    at += size
                kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
                names = ["doc_id", "piece", "start", "length", "ids_crc32", "salt"]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(rows, kinds)], names)

    schema = "doc_id long, piece int, start long, length long, ids_crc32 long, salt long"
    return docs.select("doc_id", "text").mapInArrow(run, schema)


def knapsack(price: np.ndarray, capacity: int) -> np.ndarray:
    """best[c]: the most that lengths adding up to at most c are worth; a length may repeat. price[l] belongs to length l."""
    back, held = np.zeros(capacity + 1), np.empty(capacity)  # back[capacity - c] is best[c]
    for c in range(1, capacity + 1):
        with_one = np.add(back[capacity - c + 1 : capacity + 1], price[1 : c + 1], out=held[:c])
        back[capacity - c] = max(float(with_one.max()), back[capacity - c + 1])
    return back[::-1]


def pattern_for(price: np.ndarray, best: np.ndarray, capacity: int) -> tuple:
    """A pattern traced through the knapsack's table, under prices that may have fallen since the table was made."""
    rest, left, found = np.ascontiguousarray(best[::-1]), capacity, []
    while left > 0:
        gain = price[1 : left + 1] + rest[capacity - left + 1 :]
        k = int(gain.argmax())
        if gain[k] <= 0:
            break
        found.append(k + 1)
        left -= k + 1
    return tuple(sorted(found, reverse=True))


@dataclass
class Cover:
    """A fractional solution: how often each pattern is used, so that every length is covered; its value, and the best dual bound."""

    use: dict
    value: float
    bound: float


def fractional(demand: np.ndarray, capacity: int, gap: float = 0.03, rate: float = 0.2, step: float = 0.5, spread: float = 1000.0, most_rounds: int = 500) -> Cover:
    """Multiplicative weights for the covering program, until its value is within ``gap`` of the dual bound.

    A length's price starts at its share of a bin and falls by a factor as its demand is covered; one that is covered a whole time more
    than the least covered length has no price for now. Each round makes the knapsack's table for the prices, which gives a dual bound:
    the demand's price over the best pattern's. Patterns are then traced through the table while prices go on falling, and each is used
    for ``step`` of the scarcest demand among its lengths, or of the ``spread``-th part of the most plentiful one. Covers are divided by
    the least one at the end. ``most_rounds`` is a guard; what was reached is returned with its bound."""
    kinds = np.flatnonzero(demand)
    if not len(kinds):
        return Cover({}, 0.0, 0.0)
    wanted, volume, cover = demand.astype(float), np.arange(capacity + 1) / capacity, np.zeros(capacity + 1)
    use: dict[tuple, float] = {}
    total, bound, value, low = 0.0, float((wanted * volume).sum()), math.inf, 0.0
    for _ in range(most_rounds):
        low = float(cover[kinds].min())
        price = np.where((demand > 0) & (cover <= low + 1), volume * np.exp(-rate * (cover - low)), 0.0)
        best = knapsack(price, capacity)
        bound = max(bound, float((wanted * price).sum() / best[capacity]))
        value = total / low if low > 0 else math.inf
        if value <= bound * (1 + gap):
            break
        price[price <= 0] = -math.inf
        for _ in range(max(8, len(kinds) // 10)):
            pattern = pattern_for(price, best, capacity)
            if not pattern:
                break
            counts = Counter(pattern)
            ratios = [wanted[k] / n for k, n in counts.items()]
            times = step * max(min(ratios), max(ratios) / spread)
            use[pattern] = use.get(pattern, 0.0) + times
            total += times
            for k, n in counts.items():
                more = n * times / wanted[k]
                cover[k] += more
                price[k] = price[k] * math.exp(-rate * more) if cover[k] <= low + 1 else -math.inf
    scale = low if low > 0 else math.inf
    return Cover({p: x / scale for p, x in use.items()}, value, bound)


@dataclass
class Plan:
    """Patterns and whole multiplicities that hold each length exactly as often as it occurs. The first ``by_program`` patterns come from
    the rounded program, the others from the completion; ``value`` and ``bound`` are those of the program."""

    patterns: list
    by_program: int
    value: float
    bound: float

    def bins(self) -> tuple[int, int]:
        """Bins of the program and of the completion."""
        return tuple(sum(t for _, t in part) for part in (self.patterns[: self.by_program], self.patterns[self.by_program :]))


#: How the program's patterns are rounded: an order (the fullest first, or those of the largest length first; then the most used) and
#: the share of a bin that a pattern may leave empty.
FULLEST, LARGEST = (lambda p, x: (-sum(p), -x, p)), (lambda p, x: (-p[0], -sum(p), -x, p))
ROUNDINGS = ((FULLEST, 0.0), (FULLEST, 0.001), (LARGEST, 0.05))


def rounded(use: dict, demand: np.ndarray, least: float, order) -> tuple[list, np.ndarray]:
    """Patterns and whole multiplicities, each use rounded up while the demand lasts, and the demand left. Patterns that fill less than
    ``least`` are left out: the completion fills such room better."""
    left, made = demand.tolist(), []
    for pattern, x in sorted(((p, x) for p, x in use.items() if sum(p) >= least), key=lambda item: order(*item)):
        counts = Counter(pattern)
        times = min(math.ceil(x - 1e-9), *(left[k] // n for k, n in counts.items()))
        if times > 0:
            made.append((pattern, times))
            for k, n in counts.items():
                left[k] -= n * times
    return made, np.array(left)


def plan(histogram: dict[int, int], capacity: int = 4096, gap: float = 0.03) -> Plan:
    """The program's solution, rounded in several ways, each completed by best fit; the plan of the fewest bins stays, and of such plans
    the one that owes most bins to the program. A length that fills a bin alone is a pattern of its own."""
    demand = np.zeros(capacity + 1, np.int64)
    for length, n in histogram.items():
        demand[length] = n
    alone: list[tuple[tuple, int]] = [((capacity,), int(demand[capacity]))] if demand[capacity] else []
    demand[capacity] = 0
    cover = fractional(demand, capacity, gap)
    plans = []
    for order, slack in ROUNDINGS:
        made, left = rounded(cover.use, demand, capacity * (1 - slack), order)
        plans.append(Plan(alone + made + _best_fit(left, capacity), len(alone + made), cover.value, cover.bound))
    return min(plans, key=lambda p: (sum(p.bins()), -p.bins()[0]))


def _best_fit(left: np.ndarray, capacity: int) -> list[tuple[tuple, int]]:
    """Fills bins from the largest remaining length, each time with the subset of remaining lengths that leaves the least room,
    and repeats a filling as often as counts allow."""
    left, out = left.copy(), []
    while left.any():
        first = int(np.flatnonzero(left)[-1])
        spare = left.copy()
        spare[first] -= 1
        now = [first, *_fill(spare, capacity - first)]
        kinds, n = np.unique(now, return_counts=True)
        times = max(1, int((left[kinds] // n).min()))
        out.append((tuple(sorted(now, reverse=True)), times))
        left[kinds] -= n * times
    return out


def _fill(spare: np.ndarray, room: int) -> list[int]:
    """The lengths that fill ``room`` as far as counts allow: reachable sums by bit sets, large lengths first, copies of a length in
    powers of two."""
    limit, steps, reach = (1 << (room + 1)) - 1, [], 1
    for k in np.flatnonzero(spare[: room + 1])[::-1].tolist():
        copies, size = min(int(spare[k]), room // k), 1
        while copies and not reach >> room & 1:
            n = min(size, copies)
            steps.append((k, n, reach))
            reach = (reach | reach << (k * n)) & limit
            copies, size = copies - n, 2 * size
        if reach >> room & 1:
            break
    total, out = reach.bit_length() - 1, []
    for k, n, before in reversed(steps):
        if not before >> total & 1:
            out += [k] * n
            total -= k * n
    return out


@dataclass
class Places:
    """Where the pieces of each length go: runs of ranks that share a pattern, by length and first rank."""

    length: np.ndarray
    first_rank: np.ndarray
    per_bin: np.ndarray
    first_bin: np.ndarray
    offset: np.ndarray

    @classmethod
    def of(cls, patterns: list[tuple[tuple, int]]) -> Places:
        rows, used, base = [], {}, 0
        for pattern, times in patterns:
            offset = 0
            kinds, n = np.unique(pattern, return_counts=True)
            for length, per_bin in zip(kinds.tolist(), n.tolist()):
                rows.append((length, used.get(length, 0), per_bin, base, offset))
                used[length] = used.get(length, 0) + per_bin * times
                offset += length * per_bin
            base += times
        rows.sort()
        return cls(*np.array(rows or np.zeros((0, 5)), np.int64).T)

    def find(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """sequence_id and offset of pieces by length and rank."""
        shift = np.int64(1) << 44
        k = np.searchsorted(self.length * shift + self.first_rank, length * shift + rank, side="right") - 1
        within = rank - self.first_rank[k]
        return self.first_bin[k] + within // self.per_bin[k], self.offset[k] + within % self.per_bin[k] * length


def pack(rows: DataFrame, capacity: int = 4096, gap: float = 0.03, bucket: int = 2048) -> DataFrame:
    """Adds sequence_id, offset and planned (whether the program placed the piece) to a written table of pieces. Ranks within a length are
    counted in buckets of about ``bucket`` rows; the pieces' salt spreads rows that are equal in all else."""
    histogram = {r[0]: r[1] for r in rows.groupBy("length").count().collect()}
    found = plan(histogram, capacity, gap)
    places, by_program = Places.of(found.patterns), found.bins()[0]
    split = rows.sparkSession.createDataFrame([(k, -(-n // bucket)) for k, n in histogram.items()], "length long, buckets int")
    salted = F.pmod(F.xxhash64("doc_id", "piece", "salt"), F.col("buckets"))
    dealt = rows.join(F.broadcast(split), "length").withColumn("bucket", salted).drop("buckets")
    sizes = dealt.groupBy("length", "bucket").count()
    before = Window.partitionBy("length").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    bases = sizes.withColumn("base", F.coalesce(F.sum("count").over(before), F.lit(0))).drop("count")
    inside = Window.partitionBy("length", "bucket").orderBy("doc_id", "piece", "ids_crc32", "salt")
    ranked = dealt.withColumn("rank", F.row_number().over(inside) - 1).join(bases, ["length", "bucket"])

    def place(batches):
        for b in batches:
            length, rank = b.column("length").to_numpy(), b.column("rank").to_numpy()
            sequence, offset = places.find(length, rank)
            added = [pa.array(sequence), pa.array(offset), pa.array(sequence < by_program)]
            yield pa.RecordBatch.from_arrays([*b.columns[:5], *added], [*b.schema.names[:5], "sequence_id", "offset", "planned"])

    wide = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("base") + F.col("rank")).alias("rank"))
    return wide.mapInArrow(place, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long, planned boolean")


def packed_documents(docs: DataFrame, capacity: int = 4096, **options) -> DataFrame:
    return pack(staged(pieces(doc_text(docs), capacity, **options), "pieces"), capacity)


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packed_documents(documents(spark, sf_dir))
