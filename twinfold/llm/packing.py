"""Best-fit packing by length patterns and non-negative least squares.

Documents become token pieces of at most ``capacity``; the histogram of piece lengths (at most
``capacity`` numbers, whatever the corpus size) is covered by *patterns* - multisets of few lengths
whose sum is at most the capacity. Repeat counts of the patterns are fitted to the histogram by
non-negative least squares, rounded down, and the rest is packed best-fit decreasing, again on counts. The
plan is a table of (length, first rank, last rank, first sequence, offset) intervals, and a piece finds its
place by its rank among the pieces of its length. Nothing but the histogram reaches the driver.

Defined results: null text is the empty text and still yields one piece (the end token alone); repeated
rows are packed each for itself; an empty table gives an empty result; ties in length are broken by
salted hash, doc_id and piece. Repeated doc_ids stay separate documents: their ranks differ. Other columns are not read.
"""

from __future__ import annotations

import base64
import zlib
from bisect import bisect_left
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from ..plans.storage import materialise, width
from .shared import per_text

PIECES = "piece int, start long, length long, ids_crc32 long"
_ENCODERS: dict[tuple[str, str], object] = {}


def _encoder(vocab_json: str, ranks_file: str | None):
    """ids of one text. The rank file holds the vocabulary of the JSON file and is some five times faster;
    a text with a special token's string takes the JSON file's own way."""
    key = (vocab_json, ranks_file or "")
    if key not in _ENCODERS:
        import public_tokenizers as vocabularies
        from tokenizers import Tokenizer

        slow = Tokenizer.from_file(vocab_json)
        special = [t.content for t in slow.get_added_tokens_decoder().values()]
        if ranks_file:
            import tiktoken

            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(ranks_file, "rb"))}
            fast = tiktoken.Encoding("ranks", pat_str=vocabularies.PATTERN, mergeable_ranks=ranks, special_tokens={})

            def encode(text: str) -> list[int]:
                if any(s in text for s in special):
                    return slow.encode(text, add_special_tokens=False).ids
                return fast.encode_ordinary(text)
        else:

            def encode(text: str) -> list[int]:
                return slow.encode(text, add_special_tokens=False).ids

        _ENCODERS[key] = encode
    return _ENCODERS[key]


def token_pieces(docs: DataFrame, vocab_json: str, ranks_file: str | None = None, capacity: int = 1024, end_id: int = 2, with_ids: bool = False) -> DataFrame:
    """Pieces of at most ``capacity`` tokens; a longer document's first piece takes the remainder."""

    def start():
        encode = _encoder(vocab_json, ranks_file)

        def cut(texts: list) -> dict[str, list]:
            out: dict[str, list] = {k: [] for k in ("_row", "piece", "start", "length", "ids_crc32", "ids")}
            for row, text in enumerate(texts):
                ids = np.array([*encode(text or ""), end_id], dtype="<u4")
                first = (len(ids) - 1) % capacity + 1
                for k, (a, b) in enumerate(zip([0, *range(first, len(ids), capacity)], range(first, len(ids) + 1, capacity))):
                    values = (row, k, a, b - a, zlib.crc32(ids[a:b].tobytes()), ids[a:b].tolist() if with_ids else None)
                    for name, v in zip(out, values):
                        out[name].append(v)
            return out

        return cut

    return per_text(docs, start, PIECES + (", ids array<int>" if with_ids else ""))


def patterns_for(counts: dict[int, int], capacity: int, parts: int = 4, per_length: int = 8, slack: int = 0) -> list[tuple[int, ...]]:
    """Patterns of at most ``parts`` occurring lengths that fill the capacity as far as possible.

    Each length is completed by pairs (its best complement), by triples and by quadruples over a spread of
    second lengths; so there are O(lengths * per_length) patterns, bounded by the capacity alone.
    """
    have = sorted(k for k, v in counts.items() if v > 0)
    found: set[tuple[int, ...]] = set()

    def best(room: int) -> int | None:
        i = bisect_left(have, room + 1) - 1
        return have[i] if i >= 0 else None

    for a in have:
        if a >= capacity - slack:
            found.add((a,))
            continue
        spread = sorted({round(x) for x in np.linspace(0, len(have) - 1, per_length)})
        for b in [have[i] for i in spread] + [best(capacity - a)]:
            if b is None or a + b > capacity:
                continue
            c = best(capacity - a - b)
            found.add(tuple(sorted(x for x in (a, b, c) if x)))
            if parts >= 4 and c is not None and (half := best((capacity - a - b) // 2)) is not None:
                d = best(capacity - a - b - half)
                found.add(tuple(sorted(x for x in (a, b, half, d) if x)))
        if (c := best(capacity - a)) is not None:
            found.add(tuple(sorted((a, c))))
        if a <= capacity:
            found.add((a,) * max(1, min(parts, capacity // a)))
    return sorted(p for p in found if sum(p) <= capacity)


def nnls_fit(patterns: list[tuple[int, ...]], counts: dict[int, int], capacity: int, sweeps: int = 25) -> np.ndarray:
    """Repeat counts x >= 0 minimising |A x - histogram|^2 by cyclic coordinate descent over sparse columns.
    Full patterns go first, so that waste is taken up only where nothing fuller fits."""
    size = max(counts, default=0) + 1
    rest = np.zeros(size)
    for k, v in counts.items():
        rest[k] = v
    columns = [tuple(Counter(p).items()) for p in patterns]
    norms = [sum(m * m for _, m in c) for c in columns]
    x = np.zeros(len(patterns))
    order = sorted(range(len(patterns)), key=lambda i: (capacity - sum(patterns[i]), -max(patterns[i]), i))
    scale = max(1.0, float(rest.max(initial=0)))
    for _ in range(sweeps):
        moved = 0.0
        for i in order:
            step = sum(m * rest[k] for k, m in columns[i]) / norms[i]
            step = max(step, -x[i])
            if step:
                x[i] += step
                moved = max(moved, abs(step))
                for k, m in columns[i]:
                    rest[k] -= m * step
        if moved < 1e-6 * scale:
            break
    return x


def plan(counts: dict[int, int], capacity: int = 1024) -> tuple[list[tuple[int, int, int, int, int]], int]:
    """Intervals (length, first rank, last rank, first sequence, offset) and the number of sequences.
    An interval's r-th rank goes to sequence first + r, at that offset."""
    left = {k: int(v) for k, v in counts.items() if v > 0}
    used = dict.fromkeys(left, 0)
    out: list[tuple[int, int, int, int, int]] = []
    sequences = 0

    def place(pattern: tuple[int, ...], times: int) -> None:
        nonlocal sequences
        offset = 0
        for k in sorted(pattern, reverse=True):
            out.append((k, used[k], used[k] + times - 1, sequences, offset))
            used[k] += times
            left[k] -= times
            offset += k
        sequences += times

    for k in [k for k in left if k >= capacity]:
        place((k,), left[k])
    patterns = patterns_for({k: v for k, v in left.items() if v}, capacity)
    fitted = nnls_fit(patterns, {k: v for k, v in left.items() if v}, capacity)
    for i in sorted(range(len(patterns)), key=lambda i: (capacity - sum(patterns[i]), -fitted[i], i)):
        if capacity - sum(patterns[i]) > capacity // 256:
            continue  # wasteful patterns only balance the fit; their documents are residuals
        times = min([int(fitted[i] + 1e-9), *(left[k] // m for k, m in Counter(patterns[i]).items())])
        if times > 0:
            place(patterns[i], times)
    # Residuals, still as counts: fill one bin from the largest length down with the best fit, and repeat that bin as often as the counts allow.
    have = sorted(k for k, v in left.items() if v)
    while have:
        room, bin_, spent = capacity, [], Counter()
        while have and room >= have[0]:
            i = bisect_left(have, room + 1) - 1
            while i >= 0 and left[have[i]] <= spent[have[i]]:
                i -= 1
            if i < 0:
                break
            bin_.append(have[i])
            spent[have[i]] += 1
            room -= have[i]
        if len(bin_) > 1 and room:  # the last member may be exchanged with a pair that closes the gap
            bin_ = _close(bin_, room, left, spent, have)
            spent = Counter(bin_)
        place(tuple(bin_), max(1, min(left[k] // m for k, m in spent.items())))
        have = [k for k in have if left[k] > 0]
    return out, sequences


def _close(bin_: list[int], room: int, left: dict[int, int], spent: Counter, have: list[int]) -> list[int]:
    """Replace the last length by the pair of lengths that fills its place and the gap best."""
    *head, last = bin_
    space, best = last + room, (room, bin_)
    taken = Counter(head)
    for a in have:
        if a * 2 > space or best[0] == 0:
            break
        i = bisect_left(have, space - a + 1) - 1
        while i >= 0:
            b = have[i]
            if left[b] > taken[b] + (a == b) and left[a] > taken[a]:
                if space - a - b < best[0]:
                    best = (space - a - b, [*head, a, b])
                break
            i -= 1
    return best[1]


def pack(pieces: DataFrame, capacity: int = 1024) -> DataFrame:
    """Adds ``sequence_id`` and ``offset`` to materialised ``pieces(doc_id, piece, length, ...)``.

    Ranks: a histogram over (length, salt) gives each salt's first rank, a window inside (length, salt) the rest.
    The salt is a hash of the piece, so that a length holding a third of all pieces is numbered by many tasks.
    """
    spark = pieces.sparkSession
    salts = max(64, 2 * width(spark))
    salted = pieces.withColumn("_salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(salts)).cast("int"))
    cells = salted.groupBy("length", "_salt").agg(F.count("*").alias("_n"))
    firsts = cells.select("length", "_salt", (F.sum("_n").over(Window.partitionBy("length").orderBy("_salt")) - F.col("_n")).alias("_first"))
    histogram = {r[0]: r[1] for r in cells.groupBy("length").agg(F.sum("_n").alias("n")).collect()}  # at most `capacity` rows
    intervals, _ = plan(histogram, capacity)
    inside = Window.partitionBy("length", "_salt").orderBy("doc_id", "piece", "ids_crc32", "start")
    ranked = salted.withColumn("_in", F.row_number().over(inside) - 1).join(F.broadcast(firsts), ["length", "_salt"]).withColumn("_rank", F.col("_first") + F.col("_in"))
    # The interval table is bounded by the capacity, so a sorted lookup in each batch replaces a range join.
    table: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
    for length in histogram:
        own = sorted(x[1:] for x in intervals if x[0] == length)
        table[length] = tuple(np.array([x[i] for x in own], dtype=np.int64) for i in (0, 2, 3))

    def look_up(batches):
        for batch in batches:
            lengths, ranks = batch.column("length").to_numpy(), batch.column("_rank").to_numpy()
            seq, off = np.empty(len(ranks), np.int64), np.empty(len(ranks), np.int64)
            for length in np.unique(lengths):
                at = np.flatnonzero(lengths == length)
                first, sequence, offset = table[int(length)]
                i = np.searchsorted(first, ranks[at], side="right") - 1
                seq[at], off[at] = sequence[i] + ranks[at] - first[i], offset[i]
            own = [batch.column(c) for c in keep]
            yield pa.RecordBatch.from_arrays([*own, pa.array(seq), pa.array(off)], names=[*keep, "sequence_id", "offset"])

    keep = list(pieces.columns)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema.fields)
    return ranked.select(*keep, "_rank").mapInArrow(look_up, f"{schema}, sequence_id long, offset long")


def pack_documents(docs: DataFrame, vocab_json: str, ranks_file: str | None = None, capacity: int = 1024, end_id: int = 2) -> DataFrame:
    """All documents to packed pieces; one pass of tokenising, kept in a materialised table."""
    return pack(materialise(token_pieces(docs, vocab_json, ranks_file, capacity, end_id), "pieces"), capacity)
