"""Repeated passages inside documents: candidate paragraphs, exact links, components.

Shared passages do not respect line ends, so paragraphs are cut by content: the hash of every
five-word shingle is a landmark where it is least within `window` consecutive shingles, and each
landmark opens a paragraph of `words` words. Equal passages of window + words + 4 words or more
hold the same paragraph wherever they stand. Paragraphs overlap or leave up to window - words words
between them, and up to window - 1 words of a passage lie before its first and behind its last.
Those are found by growth: see `grown`. A text of five words or more that is too short for a
paragraph is one as a whole.

Each paragraph has a fingerprint; paragraphs of one fingerprint are one node. Two nodes are linked
where the Jaccard similarity of their shingle sets reaches `percent`, and every such pair counts,
whatever else is in its buckets:

1. Sets that similar differ in few shingles (three at most for 16 at 80 %). Shingles are dealt over
   one part more than that by their hash, so two such sets agree on a whole part. Nodes that share
   a part are candidates. (A part that both have empty says nothing; sets that leave a part empty
   are dealt a second time. A pair is missed where both deals fail, with probability under 2e-5.)
2. Candidates of sizes a and b are linked when they share ceil(p (a + b) / (100 + p)) shingles, so
   every subset of that number is a key, named by a and b. Members of a bucket of equal sizes are all
   linked with each other; in a bucket of two sizes, each with all of the other size. A star
   around the bucket's smallest node therefore has the components of all its links, and only
   shares of subsets are compared, never pairs. Keys grow fast with `words` above about 30.

Components of the links are clusters. A cluster that occurs in two documents or more is a repeat:
its occurrence in the smallest doc_id stays, the others are removals.

Null and empty texts and those of fewer than five words have no paragraphs; rows with a null id take no part; rows that
repeat an id are one document; an empty table gives an empty result. Only the id and text
columns are read. Positions are word numbers from 0, ends exclusive.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .components import connected
from .shared import (
    _GOLD,
    _MULT,
    batch_of,
    bit_map,
    discard,
    id_text,
    mix64,
    slices,
    staged,
    text_bytes,
    word_hashes,
    word_spans,
)

SHINGLE = 5


def shingle_positions(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hash of the five-word shingle at every word of every row, laid end to end with the row's
    first place; words too near the end of their row have the largest hash. And the words' hashes."""
    raw, offsets = text_bytes(column)
    n = len(offsets) - 1
    starts, ends, row = word_spans(raw, offsets)
    h = word_hashes(raw, starts, ends)
    count = np.bincount(row, minlength=n) if n else np.zeros(0, np.int64)
    first = np.concatenate([[0], np.cumsum(count)]).astype(np.int64)
    s = np.full(len(h), np.iinfo(np.uint64).max, dtype=np.uint64)
    if len(h) >= SHINGLE:
        m = len(h) - SHINGLE + 1
        with np.errstate(over="ignore"):
            x = np.full(m, _GOLD, dtype=np.uint64)
            for k in range(SHINGLE):
                x *= _MULT
                x += h[k : k + m]
                x = mix64(x)
        whole = row[:m] == row[SHINGLE - 1 : SHINGLE - 1 + m]
        s[:m][whole] = np.minimum(x[whole], np.uint64(np.iinfo(np.uint64).max - 1))
    return s, first, count, h


def sliding(x: np.ndarray, width: int, better, back: bool) -> np.ndarray:
    """Least or greatest of `width` places from each place on (or up to it)."""
    out, have = x, 1
    while have < width:
        grow = min(have, width - have)
        nxt = out.copy()
        if grow < len(x):
            if back:
                better(out[grow:], out[:-grow], out=nxt[grow:])
            else:
                better(out[:-grow], out[grow:], out=nxt[:-grow])
        out, have = nxt, have + grow
    return out


def landmarks(s: np.ndarray, first: np.ndarray, count: np.ndarray, window: int) -> np.ndarray:
    """Places whose hash is the least of some `window` consecutive places; windows may hang over
    either end of a row."""
    top = np.uint64(np.iinfo(np.uint64).max)
    n = len(count)
    row = np.repeat(np.arange(n), count)
    at = np.arange(len(s)) + (row + 1) * window  # rows stand apart, so that no window spans two
    padded = np.full(len(s) + (n + 1) * window + 1, top, dtype=np.uint64)
    padded[at] = s
    least = sliding(padded, window, np.minimum, False)
    reach = sliding(least, window, np.maximum, True)
    return np.flatnonzero((reach[at] == s) & (s != top))


def paragraph_places(s: np.ndarray, first: np.ndarray, count: np.ndarray, words: int, window: int):
    """(place, row, length) of the paragraphs: `words` words from each landmark that has them behind
    it, and the whole of a shorter text that has a shingle."""
    marks = landmarks(s, first, count, window)
    row = np.searchsorted(first, marks, side="right") - 1
    room = marks + words <= first[row + 1]
    short = np.flatnonzero((count >= SHINGLE) & (count < words))
    length = np.concatenate([np.full(int(room.sum()), words), count[short]])
    return np.concatenate([marks[room], first[short]]), np.concatenate([row[room], short]), length


def paragraphs_at(s: np.ndarray, places: np.ndarray, length: np.ndarray, words: int):
    """(shingle hashes of 32 bits, fingerprint) of the paragraphs that open at `places`; a short one
    repeats its last shingle."""
    width = words - SHINGLE + 1
    if len(places):
        grid = s[places[:, None] + np.minimum(np.arange(width), (length - SHINGLE)[:, None])]
    else:
        grid = np.zeros((0, width), np.uint64)
    with np.errstate(over="ignore"):
        f = np.full(len(places), _GOLD, dtype=np.uint64)
        for k in sorted({*range(0, width, SHINGLE), width - 1}):
            f = mix64(f * _MULT + grid[:, k])
    return grid & np.uint64(0xFFFFFFFF), f.view(np.int64)


def shared_least(a: int, b: int, percent: int) -> int:
    """Shingles that sets of sizes a and b have in common at the threshold."""
    return -(-percent * (a + b) // (100 + percent))


def most_apart(width: int, percent: int) -> int:
    """The largest symmetric difference of two linked sets of up to `width` shingles."""
    return max(n - 2 * shared_least(n, 0, percent) for n in range(2, 2 * width + 1))


def distinct_in(grid: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows sorted, and where a value stands for the first time."""
    x = np.sort(grid, axis=1)
    new = np.ones(x.shape, dtype=bool)
    new[:, 1:] = x[:, 1:] != x[:, :-1]
    return x, new


def part_keys(grid: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, key, size of the row's set): a key for every part of a set that isn't empty."""
    x, new = distinct_in(grid)
    parts = most_apart(grid.shape[1], percent) + 1
    rows, keys = [], []
    at = np.arange(len(x))
    for deal in range(2):
        with np.errstate(over="ignore"):
            h = mix64(x[at] + np.uint64(deal + 1) * _GOLD)
            part = (h >> np.uint64(32)) % np.uint64(parts)
            part[~new[at]] = parts
            filled = np.zeros(len(at), dtype=np.int64)
            for p in range(parts):
                mine = part == p
                here = np.flatnonzero(mine.any(axis=1))
                filled[here] += 1
                total = (h * mine).sum(axis=1, dtype=np.uint64)[here]
                rows.append(at[here])
                keys.append(mix64(total + np.uint64(deal * parts + p + 1) * _GOLD))
        at = at[filled < parts]
    row = np.concatenate(rows)
    return row, np.concatenate(keys).view(np.int64), new.sum(axis=1)[row]


def subset_keys(grid: np.ndarray, mixed: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, key, side) of the subsets that name links; side 0: between sets of one size, 1 and 2:
    the smaller and the larger of two sizes, for rows in `mixed` only."""
    x, new = distinct_in(grid)
    size = new.sum(axis=1)
    rows, keys, sides = [np.zeros(0, np.int64)], [np.zeros(0, np.uint64)], [np.zeros(0, np.int32)]
    for a in np.unique(size).tolist():
        at = np.flatnonzero(size == a)
        h = mix64(x[at][new[at]].reshape(len(at), a))
        for b in range(1, grid.shape[1] + 1):
            least = shared_least(a, b, percent)
            if least > min(a, b):
                continue
            who = np.arange(len(at)) if a == b else np.flatnonzero(mixed[at])
            if not len(who):
                continue
            cut = np.array(list(combinations(range(a), a - least)), dtype=np.int64)
            with np.errstate(over="ignore"):
                total = h[who].sum(axis=1, dtype=np.uint64)
                lost = h[who][:, cut].sum(axis=2, dtype=np.uint64)
                key = mix64(total[:, None] - lost + np.uint64(min(a, b) * 1000 + max(a, b)) * _GOLD)
            rows.append(np.repeat(at[who], len(cut)))
            keys.append(key.reshape(-1))
            sides.append(np.full(key.size, 0 if a == b else 1 if a < b else 2, dtype=np.int32))
    return np.concatenate(rows), np.concatenate(keys).view(np.int64), np.concatenate(sides)


def wanted_prints(keys: DataFrame):
    """The prints' bit map as a broadcast variable (None inside when there are too many)."""
    return keys.sparkSession.sparkContext.broadcast(bit_map(keys, F.col("print")))


def cut_paragraphs(docs: DataFrame, words: int, window: int, fields: str, shipped=None, percent: int = 80) -> DataFrame:
    """A row per paragraph with some of doc_id, at, n (its words), print, shingles (hashes of 32 bits), or a row
    per part of its set with print, key, size.

    `shipped` restricts the scan to a bit map's prints; what passes by chance is dropped by the
    join that follows. `shingles` and `key` need each print once per slice only.
    """
    kinds = {"doc_id": "long", "at": "int", "n": "int", "print": "long", "shingles": "array<int>", "key": "long", "size": "int"}
    arrow = {"long": pa.int64(), "int": pa.int32(), "array<int>": pa.list_(pa.int32())}
    names = fields.split()
    schema = pa.schema([(n, arrow[kinds[n]]) for n in names])

    def run(batches):
        wanted = shipped.value if shipped is not None else None
        for part in slices(batches, 1 << 20):
            s, first, count, _ = shingle_positions(part.column(1))
            marks, row, length = paragraph_places(s, first, count, words, window)
            grid, prints = paragraphs_at(s, marks, length, words)
            keep = np.arange(len(marks)) if wanted is None else np.flatnonzero(wanted.has(prints))
            if "shingles" in names or "key" in names:
                keep = keep[np.unique(prints[keep], return_index=True)[1]]
            made = {}
            if "key" in names:
                of, keys, size = part_keys(grid[keep], percent)
                keep = keep[of]
                made = {"key": lambda: keys, "size": lambda: size.astype(np.int32)}
            made |= {"print": lambda: prints[keep], "at": lambda: (marks - first[row])[keep].astype(np.int32)}
            made["n"] = lambda: length[keep].astype(np.int32)
            made["doc_id"] = lambda: part.column(0).to_numpy(zero_copy_only=False)[row[keep]]
            made["shingles"] = lambda: list(grid[keep].astype(np.uint32).view(np.int32))
            yield batch_of(schema, *[made[n]() for n in names])

    return docs.where("doc_id IS NOT NULL").mapInArrow(run, ", ".join(f"{n} {kinds[n]}" for n in names))


def among(places: DataFrame, shipped) -> DataFrame:
    """The rows (doc_id, at, n, print) whose print is in a bit map, and a few others."""

    def run(batches):
        for part in slices(batches):
            if shipped.value is not None:
                part = part.filter(pa.array(shipped.value.has(part.column(3).to_numpy())))
            yield part

    return places.select("doc_id", "at", "n", "print").mapInArrow(run, "doc_id long, at int, n int, print long")


def subset_rows(sets: DataFrame, percent: int) -> DataFrame:
    """print, key, side of every row (print, mixed, shingles)."""
    schema = pa.schema([("print", pa.int64()), ("key", pa.int64()), ("side", pa.int32())])

    def run(batches):
        for part in slices(batches, 1 << 17):
            lists = part.column(2)
            grid = lists.flatten().to_numpy(zero_copy_only=False).view(np.uint32).astype(np.uint64).reshape(len(lists), -1)
            row, key, side = subset_keys(grid, part.column(1).to_numpy(zero_copy_only=False), percent)
            yield batch_of(schema, part.column(0).to_numpy()[row], key, side)

    return sets.select("print", "mixed", "shingles").mapInArrow(run, "print long, key long, side int")


def near_links(docs: DataFrame, words: int, window: int, percent: int) -> DataFrame:
    """Links (a, b) of prints whose components are those of all pairs at the threshold."""
    bucket = Window.partitionBy("key")
    ends = lambda c: (F.min(c).over(bucket), F.max(c).over(bucket))
    (low, high), (small, large) = ends("print"), ends("size")
    met = cut_paragraphs(docs, words, window, "print key size", percent=percent).select(
        "print", (low != high).alias("met"), (small != large).alias("mixed")
    )
    candidates = staged(met.where("met").groupBy("print").agg(F.max("mixed").alias("mixed")), "candidates")
    found = cut_paragraphs(docs, words, window, "print shingles", wanted_prints(candidates)).dropDuplicates(["print"])
    (low, high), (small, large) = ends("print"), ends("side")
    starred = subset_rows(found.join(candidates, "print"), percent).select(
        "print", low.alias("hub"), small.alias("small"), large.alias("large")
    )
    links = starred.where("print <> hub AND (large = 0 OR small <> large)").select(F.col("hub").alias("a"), F.col("print").alias("b"))
    links = staged(links.distinct(), "links")
    discard(candidates)
    return links


def repeated_passages(
    docs: DataFrame,
    words: int = 20,
    window: int = 26,
    percent: int = 80,
    id_col: str = "doc_id",
    text_col: str = "text",
) -> DataFrame:
    """doc_id, at, end, component_id, removed, grown_at, grown_end: every paragraph that repeats
    across documents, and for those to remove the words around that repeat with it.

    The texts are scanned four times (places, candidates, their sets, words around removals): only
    the places of paragraphs are kept between scans, about 12 bytes each, and never their sets.
    """
    docs = id_text(docs, id_col, text_col)
    places = staged(cut_paragraphs(docs, words, window, "doc_id at n print"), "places")
    links = near_links(docs, words, window, percent)
    component = staged(connected(links), "components")
    discard(links)
    # Copies of a paragraph collapse in the map-side part of this aggregate. Only nodes that occur
    # in two documents or have a link can belong to a repeat.
    placed = (
        places.groupBy("print")
        .agg(F.min(F.struct("doc_id", "at")).alias("first"), F.max("doc_id").alias("high"))
        .join(component.withColumnRenamed("id", "print"), "print", "left")
        .where("first.doc_id <> high OR component IS NOT NULL")
        .withColumn("component_id", F.coalesce("component", "print"))
    )
    placed = staged(placed.select("print", "component_id", "first", "high"), "placed")
    repeats = (
        placed.groupBy("component_id")
        .agg(F.min(F.struct("first.doc_id", "first.at", "print")).alias("head"), F.max("high").alias("high"))
        .where("head.doc_id <> high")
    )
    flagged = staged(placed.select("print", "component_id", "first").join(repeats.drop("high"), "component_id"), "flagged")
    discard(placed)
    # The model of a removal (see `grown`) comes along, so that occurrences are joined only once.
    exact = F.col("first.doc_id") < F.col("doc_id")
    model = F.when(exact, F.struct("first.doc_id", "first.at", "print")).otherwise(F.col("head"))
    removed = F.col("doc_id") != F.col("head.doc_id")
    found = among(places, wanted_prints(flagged.select("print"))).join(flagged, "print")
    found = found.select("doc_id", "at", "n", "print", "component_id", removed.alias("removed"), F.when(removed, model).alias("model"), exact.alias("exact"))
    found = staged(found, "occurrences")
    discard(places)
    discard(flagged)
    more = staged(grown(docs, found.where((F.col("n") == words) & F.col("removed")), words, window), "grown")
    return found.join(more, ["doc_id", "at", "print"], "left").select(
        "doc_id",
        F.col("at").cast("long").alias("at"),
        (F.col("at") + F.col("n")).cast("long").alias("end"),
        "component_id",
        "removed",
        (F.col("at") - F.coalesce("before", F.lit(0))).cast("long").alias("grown_at"),
        (F.col("at") + F.col("n") + F.coalesce("behind", F.lit(0))).cast("long").alias("grown_end"),
    )


def surroundings(docs: DataFrame, words: int, window: int, shipped) -> DataFrame:
    """doc_id, at, print, side, near: hashes of the up to `window` words before (side 0, nearest
    first) or behind (side 1) the paragraphs in the bit map (see `slot`)."""
    schema = pa.schema([("doc_id", pa.int64()), ("at", pa.int32()), ("print", pa.int64()), ("side", pa.int32()), ("near", pa.binary())])

    def run(batches):
        wanted = shipped.value
        for part in slices(batches, 1 << 20):
            s, first, count, h = shingle_positions(part.column(1))
            marks, row, length = paragraph_places(s, first, count, words, window)
            full = length == words
            marks, row = marks[full], row[full]
            _, prints = paragraphs_at(s, marks, length[full], words)
            ids, at = part.column(0).to_numpy(zero_copy_only=False)[row], marks - first[row]
            for side in (0, 1):
                keep = np.arange(len(marks)) if wanted is None else np.flatnonzero(wanted.has(prints ^ (at << 3) ^ (ids << 7) ^ side))
                begin = marks[keep] - 1 if side == 0 else marks[keep] + words
                room = np.minimum(window, marks[keep] - first[row[keep]] if side == 0 else first[row[keep] + 1] - begin)
                place = begin[:, None] + np.arange(window) * (2 * side - 1)
                near = h[np.clip(place, 0, max(len(h) - 1, 0))].astype(np.uint32) if len(keep) else np.zeros((0, window), np.uint32)
                cut = [x.tobytes()[: 4 * k] for x, k in zip(near, room.tolist())]
                yield batch_of(schema, ids[keep], at[keep].astype(np.int32), prints[keep], np.full(len(keep), side, np.int32), cut)

    return docs.where("doc_id IS NOT NULL").mapInArrow(run, "doc_id long, at int, print long, side int, near binary")


def slot():
    """A hash of (doc_id, at, print, side)."""
    mixed = F.col("print").bitwiseXOR(F.shiftleft(F.col("at").cast("long"), 3)).bitwiseXOR(F.shiftleft("doc_id", 7))
    return mixed.bitwiseXOR(F.col("side").cast("long"))


def with_pattern(rows: DataFrame, patterns: DataFrame) -> DataFrame:
    """`rows` with the pattern of their (model, side). Models of more than a thousandth of the rows
    (2,048 at most) are broadcast, so that a very common passage stays spread over tasks."""
    total = rows.count()
    counts = rows.groupBy("model", "side").agg(F.count("*").alias("k")).where(F.col("k") > max(64, total // 1024)).drop("k")
    hot = patterns.join(F.broadcast(counts), ["model", "side"]).withColumnRenamed("pattern", "hot")
    marked = rows.join(F.broadcast(hot), ["model", "side"], "left")
    rest = marked.where("hot IS NULL").drop("hot").join(patterns, ["model", "side"])
    return marked.where("hot IS NOT NULL").withColumnRenamed("hot", "pattern").unionByName(rest)


def common_words(pairs: DataFrame) -> DataFrame:
    """doc_id, at, print, side, n: leading words that near and pattern have in common."""
    schema = pa.schema([("doc_id", pa.int64()), ("at", pa.int32()), ("print", pa.int64()), ("side", pa.int32()), ("n", pa.int32())])

    def run(batches):
        for part in slices(batches):
            n = []
            for x, y in zip(part.column(4).to_pylist(), part.column(5).to_pylist()):
                k = min(len(x), len(y or b"")) // 4
                differ = np.frombuffer(x, np.uint32, k) != np.frombuffer(y or b"", np.uint32, k)
                n.append(int(differ.argmax()) if differ.any() else k)
            yield batch_of(schema, *[part.column(c) for c in range(4)], n)

    return pairs.select("doc_id", "at", "print", "side", "near", "pattern").mapInArrow(run, "doc_id long, at int, print long, side int, n int")


def grown(docs: DataFrame, gone: DataFrame, words: int, window: int) -> DataFrame:
    """doc_id, at, print, before, behind: how many words around a removal repeat with it.

    A removal's model is the first occurrence of its print or, where no smaller document holds it,
    its cluster's first occurrence. Removals of a document that touch or overlap make a run, those
    with a model of the first kind together and the others by model and distance; the
    first and last of a run are compared with their models word by word, outward to the first
    difference. A passage that such a model shares has no more than `window` words beyond the run
    (each `window` places open a paragraph), so all of an equal passage of window + words + 4
    words or more is covered. Hashes of words have 32 bits.
    """
    near = F.when(~F.col("exact"), F.struct("model.doc_id", F.col("at") - F.col("model.at")))
    run = Window.partitionBy("doc_id", near).orderBy("at", "print")
    opens = F.coalesce(F.lag("at").over(run) + words < F.col("at"), F.lit(True))
    ends = F.coalesce(F.lead("at").over(run) > F.col("at") + words, F.lit(True))
    sides = F.array_compact(F.array(F.when(opens, F.lit(0)), F.when(ends, F.lit(1))))
    edges = gone.select("doc_id", "at", "print", "model", sides.alias("sides"))
    edges = staged(edges.select("doc_id", "at", "print", "model", F.explode("sides").alias("side")), "edges")
    asked = edges.withColumn("own", F.lit(0)).union(
        edges.select("model.doc_id", "model.at", "model.print", "model", "side", F.lit(1)).distinct()
    )
    shipped = docs.sparkSession.sparkContext.broadcast(bit_map(asked, slot()))
    seen = staged(surroundings(docs, words, window, shipped).join(asked, ["doc_id", "at", "print", "side"]), "near")
    patterns = seen.where("own = 1").groupBy("model", "side").agg(F.min("near").alias("pattern"))
    both = with_pattern(seen.where("own = 0"), patterns)
    least = lambda k: F.min(F.when(F.col("side") == k, F.col("n")))
    return common_words(both).groupBy("doc_id", "at", "print").agg(least(0).alias("before"), least(1).alias("behind"))


def removal_spans(found: DataFrame) -> DataFrame:
    """doc_id, spans (array of at, end; merged, in order) of the words to remove, grown to all that
    repeats around the paragraphs."""
    ordered = F.array_sort(F.collect_set(F.struct(F.col("grown_at").alias("at"), F.col("grown_end").alias("end"))))
    empty = F.array().cast("array<struct<at:bigint,end:bigint>>")

    def join(done, x):
        last = F.element_at(done, -1)
        grown = F.concat(
            F.slice(done, F.lit(1), F.size(done) - 1),
            F.array(F.struct(last["at"].alias("at"), F.greatest(last["end"], x["end"]).alias("end"))),
        )
        return F.when((F.size(done) > 0) & (x["at"] <= F.try_element_at(done, F.lit(-1))["end"]), grown).otherwise(
            F.concat(done, F.array(F.struct(x["at"].alias("at"), x["end"].alias("end"))))
        )

    return (
        found.where("removed")
        .groupBy("doc_id")
        .agg(ordered.alias("spans"))
        .select("doc_id", F.aggregate("spans", empty, join).alias("spans"))
    )
