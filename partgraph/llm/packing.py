"""Best-fit packing into fixed-length sequences by a grouping genetic algorithm on islands.

Documents are encoded once; the pieces (lengths and checksums, no ids) are dealt into packing groups of about GROUP
pieces by hash. In a group, best-fit decreasing gives the first grouping. A group with more bins than a proven lower bound
evolves: its ISLANDS are rows of a table, each a population of groupings, bred by tasks of their own; a child gets whole
well-filled bins of a second parent, loses its own bins that repeat their pieces, and best-fits the displaced pieces, after trades that fill bins better.
Bins that one or two pieces fill exactly are settled, by proof, and no island carries them.
After each epoch, a job, every island sends its elite to the next one. Islands whose group reached the bound rest; the
bound proves that nothing is left to gain. Last, the bins that stayed at most half full are packed across groups.

Cases: a null or empty text is one piece holding the end id alone; a text longer than the capacity is cut into full
pieces behind a shorter first one; repeated rows are packed each; ties go to the first bin found; an empty table gives
no rows; other columns are ignored. Equal rows are interchangeable: which of them goes where depends on the files.
"""

from __future__ import annotations

import bisect
import itertools
import json
import random
import re
import zlib
from collections.abc import Callable
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import _WS, SPLIT, byte_letters
from .common import mix, spill

CAPACITY = 2048
END_ID = 0
#: Pieces in a packing group, on average.
GROUP = 8192
ISLANDS, POPULATION, EPOCHS, GENERATIONS = 4, 4, 3, 12
#: Pieces of a bin, and loose ones, of which pairs are tried in a trade.
TRADED = 24
#: Two white spaces before another character: the last one goes with what follows, which the split pattern finds by looking ahead.
RUN = rf"[{_WS}][{_WS}][^{_WS}]"
_CUT = re.compile(rf"[{_WS}](?=[{_WS}][^{_WS}])")
#: The split pattern without looking ahead, which a faster engine takes; the same for parts that hold no such run.
AHEAD = rf"[{_WS}]+(?![^{_WS}])|"
PLAIN = SPLIT.pattern.replace(AHEAD, "")
PIECE = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint, deal bigint"


@lru_cache(maxsize=4)
def fast_encoder(path: str, pattern: str = SPLIT.pattern):
    """tiktoken on the vocabulary of a tokenizers file: the same ids, several times faster."""
    import tiktoken

    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    back = {c: b for b, c in byte_letters().items()}
    special = {t["content"]: t["id"] for t in spec["added_tokens"]}
    ranks = {bytes(back[c] for c in t): i for t, i in spec["model"]["vocab"].items() if t not in special}
    return tiktoken.Encoding("byte_bpe", pat_str=pattern, mergeable_ranks=ranks, special_tokens=special)


def encoder(path: str) -> Callable[[str, bool], np.ndarray]:
    """Ids of a text; the flag says that RUN is in it."""
    plain = fast_encoder(path, PLAIN)

    def run(text: str, runs: bool) -> np.ndarray:
        if not runs:
            return plain.encode_to_numpy(text, allowed_special="all")
        if any(s in text for s in plain.special_tokens_set):  # white space before a special token ends its part
            return fast_encoder(path).encode_to_numpy(text, allowed_special="all")
        cuts = [0, *(m.end() for m in _CUT.finditer(text)), len(text)]
        return np.concatenate([plain.encode_to_numpy(text[a:b], allowed_special="all") for a, b in zip(cuts, cuts[1:], strict=False)])

    return run


def pieces(docs: DataFrame, path: str, capacity: int = CAPACITY) -> DataFrame:
    """One row for each piece of each document."""
    import pyarrow as pa
    import pyarrow.compute as pc

    def run(batches):
        encode = encoder(path)
        for batch in batches:
            rows: list[tuple] = []
            met: dict[tuple, int] = {}
            runs = pc.match_substring_regex(batch.column(1), RUN).to_pylist()
            for doc, text, ahead in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), runs, strict=True):
                ids = np.append(encode(text, ahead) if text else np.zeros(0, np.uint32), np.uint32(END_ID)).astype("<u4")
                cuts = [0, *range(len(ids) % capacity or capacity, len(ids) + 1, capacity)]
                for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
                    row = (doc, k, a, b - a, zlib.crc32(ids[a:b].tobytes()))
                    met[row] = met.get(row, 0) + 1
                    rows.append((*row, met[row]))
            cols = list(zip(*rows, strict=True)) or [[]] * 6
            with np.errstate(over="ignore"):
                # equal pieces of equal rows are dealt apart by their count in the batch
                salt = np.array([x or 0 for x in cols[0]], np.int64).view(np.uint64)
                for c in (1, 4, 5):
                    salt = mix(salt * np.uint64(0x9E3779B97F4A7C15) + np.array(cols[c], np.uint64))
                salt = mix(salt) >> np.uint64(1)
            yield pa.RecordBatch.from_arrays(
                [pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int32()), *(pa.array(c, pa.int64()) for c in cols[2:5]), pa.array(salt.astype(np.int64))],
                ["doc_id", "piece", "start", "length", "ids_crc32", "deal"],
            )

    return docs.selectExpr("cast(doc_id as bigint) doc_id", "text").mapInArrow(run, PIECE)


# ---- packing of one group ---------------------------------------------------------------------


def best_fit(items: list[int], size: list[int], capacity: int, bins: list[list[int]] | None = None) -> list[list[int]]:
    """Put items, largest first, each into the fullest bin with room (of ``bins``, copied, or a new one)."""
    bins, get = [list(b) for b in bins or []], size.__getitem__
    room_of: list[list[int]] = [[] for _ in range(capacity + 1)]
    mask = 0
    for i, b in enumerate(bins):
        room = capacity - sum(map(get, b))
        room_of[room].append(i)
        mask |= 1 << room
    for x in sorted(items, key=size.__getitem__, reverse=True):
        s = size[x]
        if open_ := mask >> s:
            room = s + (open_ & -open_).bit_length() - 1
            i = room_of[room].pop()
            if not room_of[room]:
                mask ^= 1 << room
            bins[i].append(x)
        else:
            room, i = capacity, len(bins)
            bins.append([x])
        room_of[room - s].append(i)
        mask |= 1 << (room - s)
    return bins


def lower_bound(size: list[int], capacity: int) -> int:
    """No packing has fewer bins: volume, and pieces that cannot share a bin, over thresholds k."""
    s = np.sort(np.asarray(size, np.int64))
    total = np.concatenate([[0], np.cumsum(s)])
    best = -(-int(total[-1]) // capacity)
    half = int(np.searchsorted(s, capacity // 2, "right"))
    for k in {0, *s[:half].tolist()}:
        low, high = int(np.searchsorted(s, k)), int(np.searchsorted(s, capacity - k, "right"))
        high = max(high, half)
        middle, large = high - half, len(s) - high
        free = middle * capacity - int(total[high] - total[half])
        best = max(best, large + middle + max(0, -(-(int(total[half] - total[low]) - free) // capacity)))
    return best


def settle(bins: list[list[int]], size: list[int], capacity: int) -> tuple[list[list[int]], list[list[int]]]:
    """Bins that some best grouping holds as they are, and the others.

    These are the bins that one or two pieces fill exactly. A piece of the whole capacity is alone in any grouping; where
    pieces that fill a bin together lie apart, one may change places with all that lies beside the other, which is no
    larger: a grouping of as many bins has them together.
    """
    fixed, free = [], []
    for b in bins:
        (fixed if len(b) <= 2 and sum(size[x] for x in b) == capacity else free).append(b)
    return fixed, free


def _fitness(bins: list[list[int]], size: list[int], capacity: int) -> tuple[int, float]:
    get = size.__getitem__
    return -len(bins), sum((sum(map(get, b)) / capacity) ** 2 for b in bins) / max(1, len(bins))


@lru_cache(maxsize=128)
def _couples(n: int, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    low, high = np.triu_indices(n, 1)
    return low, high, (most - 1 - low) * most + high


def _pair_sums(have: list[tuple[int, int]], most: int) -> list[int]:
    """Sums of two of the ``most`` smallest loose pieces, ascending, each with both places: (sum, most - 1 - low, high) as one number."""
    least = np.array([h for h, _ in have[:most]], np.int64)
    low, high, code = _couples(len(least), most)
    return np.sort((least[low] + least[high]) * (most * most) + code).tolist()


def trade(bins: list[list[int]], loose: list[int], size: list[int], capacity: int) -> tuple[list[list[int]], list[int]]:
    """Bins give one or two pieces for one or two larger loose ones that still fit: bins get fuller, loose pieces smaller."""
    have = sorted((size[x], x) for x in loose)
    out, get, most, sums = [], size.__getitem__, TRADED + 1, None
    for b in bins:
        room, gain, best = capacity - sum(map(get, b)), 0, None
        if room and have:
            for give in itertools.chain(((x,) for x in b), itertools.combinations(b[:TRADED], 2)):
                s = sum(map(get, give))
                k = bisect.bisect_right(have, (s + room, len(size))) - 1
                if k >= 0 and have[k][0] - s > gain:
                    gain, best = have[k][0] - s, (give, (k,))
                if gain < room:  # two loose pieces
                    if sums is None:
                        sums = _pair_sums(have, most)
                    j = bisect.bisect_left(sums, (s + room + 1) * most * most) - 1
                    if j >= 0 and (pair := sums[j] // (most * most)) - s > gain:
                        gain, best = pair - s, (give, (most - 1 - sums[j] // most % most, sums[j] % most))
                if gain == room:  # the bin is full
                    break
        if best:
            (give, take), sums = best, None
            b = [x for x in b if x not in give] + [have[k][1] for k in take]
            for k in reversed(take):
                del have[k]
            for x in give:
                bisect.insort(have, (size[x], x))
        out.append(b)
    return out, [x for _, x in have]


def cross(first: list[list[int]], second: list[list[int]], size: list[int], capacity: int, rng: random.Random) -> list[list[int]]:
    """Whole well-filled bins of ``second`` go into ``first``; what they displace is best-fitted again."""
    ranked = sorted(second, key=lambda b: sum(map(size.__getitem__, b)), reverse=True)
    take = ranked[: max(1, len(ranked) // 2)]
    take = [b for b in take if rng.random() < 0.5] or take[:1]
    there = {x for b in take for x in b}
    kept, loose = [*take], []
    for b in first:
        if there.isdisjoint(b):
            kept.append(b)
        else:
            loose.extend(x for x in b if x not in there)
    kept, loose = trade(kept, loose, size, capacity)
    return best_fit(loose, size, capacity, kept)


def mutate(bins: list[list[int]], size: list[int], capacity: int, rng: random.Random) -> list[list[int]]:
    """Dissolve the least-filled bin and a few others, trade their pieces with the rest, and best-fit them."""
    ranked = sorted(bins, key=lambda b: sum(map(size.__getitem__, b)))
    gone = {0, *rng.sample(range(len(ranked)), min(len(ranked), 4))} if ranked else set()
    rest = [b for i, b in enumerate(ranked) if i not in gone]
    rng.shuffle(rest)
    rest, loose = trade(rest, [x for i in gone for x in ranked[i]], size, capacity)
    return best_fit(loose, size, capacity, rest)


def founders(size: list[int], capacity: int, seed: int) -> list[list[list[int]]]:
    """First population of an island: best-fit decreasing, and variants in which a third of the bins is refilled at random."""
    rng = random.Random(seed)
    start = best_fit(list(range(len(size))), size, capacity)

    def variant() -> list[list[int]]:
        gone = set(rng.sample(range(len(start)), max(1, len(start) // 3)))
        loose = [x for i in gone for x in start[i]]
        rng.shuffle(loose)
        cut = rng.randrange(len(loose) + 1)
        return best_fit(loose[cut:], size, capacity, best_fit(loose[:cut], size, capacity, [b for i, b in enumerate(start) if i not in gone]))

    return [start, *(variant() for _ in range(POPULATION - 1))]


def breed(pop: list[list[list[int]]], size: list[int], capacity: int, goal: int, seed: int) -> list[list[list[int]]]:
    """The population after an epoch, best first; it ends early when ``goal`` bins are reached."""
    rng = random.Random(seed)
    # each grouping is scored once
    scored = sorted(((_fitness(b, size, capacity), b) for b in pop), key=lambda x: x[0], reverse=True)
    for _ in range(GENERATIONS):
        if len(scored[0][1]) <= goal:
            break
        (_, a), (_, b) = rng.sample(scored, 2)
        child = mutate(cross(a, b, size, capacity, rng), size, capacity, rng)
        scored.append((_fitness(child, size, capacity), child))
        scored.sort(key=lambda x: x[0], reverse=True)
        scored.pop()
    return [b for _, b in scored]


def _numbers(bins: list[list[int]], n: int) -> list[int]:
    out = [0] * n
    for i, b in enumerate(bins):
        for x in b:
            out[x] = i
    return out


def _bins(numbers: list[int]) -> list[list[int]]:
    out: list[list[int]] = [[] for _ in range(max(numbers, default=-1) + 1)]
    for x, i in enumerate(numbers):
        out[i].append(x)
    return [b for b in out if b]


ISLAND = "grp bigint, island int, goal int, bins int, size array<int>, pop array<array<int>>"


def islands_of(dealt: DataFrame, capacity: int) -> DataFrame:
    """(grp, rows, size, numbers, bins, goal, settled): each group's pieces, those of settled bins first, and their
    best-fit bins; ``size`` has the pieces that are left to an open group's islands."""
    ordered = F.array_sort(F.collect_list(F.struct("deal", "doc_id", "piece", "start", "length", "ids_crc32")))
    grouped = dealt.groupBy("grp").agg(ordered.alias("rows")).withColumn("size", F.transform("rows", lambda r: r["length"].cast("int")))
    import pyarrow as pa

    def run(batches):
        for batch in batches:
            order, numbers, left, bins, goal, settled = [], [], [], [], [], []
            for size in batch.column("size").to_pylist():
                fixed, free = settle(best_fit(list(range(len(size))), size, capacity), size, capacity)
                found = fixed + free
                number = _numbers(found, len(size))
                turn = [x for b in found for x in b]
                at = len(order)
                order.extend(at + x for x in turn)
                numbers.append([number[x] for x in turn])
                bins.append(len(found))
                goal.append(lower_bound(size, capacity))
                settled.append(len(fixed))
                left.append([size[x] for b in free for x in b] if bins[-1] > goal[-1] else [])
            rows = batch.column("rows")
            edges = pa.array(np.cumsum([0, *map(len, numbers)]), pa.int32())
            rows = pa.ListArray.from_arrays(edges, rows.flatten().take(pa.array(order, pa.int64())), type=rows.type)
            ints = pa.list_(pa.int32())
            yield pa.RecordBatch.from_arrays(
                [batch.column("grp"), rows, pa.array(left, ints), pa.array(numbers, ints), *(pa.array(c, pa.int32()) for c in (bins, goal, settled))],
                ["grp", "rows", "size", "numbers", "bins", "goal", "settled"],
            )

    piece = "array<struct<deal:bigint,doc_id:bigint,piece:int,start:bigint,length:bigint,ids_crc32:bigint>>"
    return grouped.select("grp", "rows", "size").mapInArrow(run, f"grp bigint, rows {piece}, size array<int>, numbers array<int>, bins int, goal int, settled int")


def evolve(open_: DataFrame, capacity: int, epochs: int = EPOCHS) -> DataFrame:
    """(grp, bins, numbers): the best grouping that the islands of each (grp, size, goal) row find."""
    import pyarrow as pa

    def epoch(number: int):
        def run(batches):
            for batch in batches:
                out = []
                for r in batch.to_pylist():
                    size, seed = r["size"], hash((r["grp"], r["island"], number))
                    pop = [_bins(x) for x in r["pop"]] if r["pop"] else founders(size, capacity, seed)
                    pop = breed(pop, size, capacity, r["goal"], seed)
                    out.append(r | {"bins": len(pop[0]), "pop": [_numbers(b, len(size)) for b in pop]})
                yield pa.RecordBatch.from_pylist(out, schema=batch.schema)

        return run

    rows = open_.select("grp", F.explode(F.sequence(F.lit(0), F.lit(ISLANDS - 1))).alias("island"), "goal", F.lit(0).alias("bins"), "size", F.array().cast("array<array<int>>").alias("pop"))
    # an island is little data and much work: a task for each, which sizes in bytes would join
    tasks = max(1, min(4096, open_.count() * ISLANDS))
    rows = spill(rows.repartition(tasks, "grp", "island").mapInArrow(epoch(0), ISLAND))
    for number in range(1, epochs):
        done = rows.where("bins <= goal").select("grp").distinct()
        busy = rows.join(done, "grp", "left_anti")
        if busy.isEmpty():
            break
        # the elite of island i takes the place of the worst of island i + 1
        elite = busy.select("grp", F.pmod(F.col("island") + 1, F.lit(ISLANDS)).cast("int").alias("island"), F.col("pop")[0].alias("elite"))
        met = busy.join(elite, ["grp", "island"]).withColumn("pop", F.concat(F.slice("pop", 1, POPULATION - 1), F.array("elite")))
        bred = met.select("grp", "island", "goal", "bins", "size", "pop").repartition(tasks, "grp", "island").mapInArrow(epoch(number), ISLAND)
        rows = spill(bred.unionByName(rows.join(done, "grp", "left_semi")), rows)
    best = rows.groupBy("grp").agg(F.min_by(F.struct("bins", F.col("pop")[0].alias("numbers")), F.struct("bins", "island")).alias("x"))
    return best.select("grp", "x.bins", "x.numbers")


def pack_pieces(dealt: DataFrame, count: int, capacity: int = CAPACITY) -> DataFrame:
    """Pieces with sequence_id and offset; ``count`` (documents) sets the number of groups."""
    groups = max(1, round(count / GROUP))
    first = spill(islands_of(dealt.withColumn("grp", F.pmod("deal", F.lit(groups))), capacity))
    # islands breed what the settled bins leave
    open_ = first.where("bins > goal").select("grp", "size", F.expr("goal - settled").alias("goal"))
    better = evolve(open_, capacity).select("grp", F.col("numbers").alias("evolved"))
    whole = F.expr("concat(slice(numbers, 1, size(numbers) - size(evolved)), transform(evolved, x -> x + settled))")
    final = first.join(better, "grp", "left").select("grp", "rows", F.coalesce(whole, "numbers").alias("numbers"))
    pieces_ = final.select("grp", F.explode(F.arrays_zip("rows", "numbers")).alias("z")).select("grp", F.col("z.numbers").alias("bin"), "z.rows.*")
    fill = pieces_.groupBy("grp", "bin").agg(F.sum("length").alias("fill"))
    merged = _merge_loose(fill.where(F.col("fill") <= capacity // 2), capacity)
    placed = pieces_.join(merged, ["grp", "bin"], "left")
    # sequence ids: the group's own bins, or negative numbers for bins merged across groups
    own = F.col("grp") * F.lit(1 << 20) + F.col("bin")
    in_bin = Window.partitionBy("grp", "bin").orderBy("deal", "doc_id", "piece", "start").rowsBetween(Window.unboundedPreceding, -1)
    offset = F.coalesce(F.sum("length").over(in_bin), F.lit(0)) + F.coalesce("base", F.lit(0))
    return placed.select("doc_id", "piece", "start", "length", "ids_crc32", F.coalesce("merged", own).cast("bigint").alias("sequence_id"), offset.cast("bigint").alias("offset"))


def _merge_loose(loose: DataFrame, capacity: int) -> DataFrame:
    """(grp, bin, merged, base): bins at most half full (one for each group, about) packed together, best fit again."""
    import pyarrow as pa

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by([("grp", "ascending"), ("bin", "ascending")])
        size = table.column("fill").to_pylist()
        number, base = [0] * len(size), [0] * len(size)
        deal = table.column("deal")[0].as_py()
        for i, b in enumerate(best_fit(list(range(len(size))), size, capacity)):
            at = 0
            for x in b:
                number[x], base[x] = -1 - ((deal << 20) + i), at
                at += size[x]
        return pa.table({"grp": table.column("grp"), "bin": table.column("bin"), "merged": pa.array(number, pa.int64()), "base": pa.array(base, pa.int64())})

    dealt = loose.withColumn("deal", F.expr(f"grp div {GROUP}"))
    return dealt.groupBy("deal").applyInArrow(run, "grp bigint, bin int, merged bigint, base bigint")


def pack_documents(docs: DataFrame, path: str, capacity: int = CAPACITY) -> DataFrame:
    return pack_pieces(pieces(docs, path, capacity), docs.count(), capacity)


def op6_genetic_packing(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("byte_bpe_50k.json"))
