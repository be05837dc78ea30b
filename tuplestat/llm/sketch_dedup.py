"""Near-duplicate documents with SetSketch registers.

A document's set of hashed word shingles is summed up in m registers. Each shingle throws m
exponentially distributed points, the j-th smallest of them drawn from the j-th slice of the
distribution, onto the registers in an order of its own; a register keeps the least point,
truncated to a logarithmic scale of base b. Sketches of unions are register-wise maxima, and a
register agrees in two sketches about as often as the sets' Jaccard similarity.

1. One scan writes set size, a 128-bit fingerprint of the set and the registers per row.
2. Rows with one fingerprint are one class, which its smallest id stands for.
3. Registers are banded; classes that share a band's values meet in a bucket. Buckets emit
   stars around hubs, never all pairs: one of eight keyed orders names the hub of a bucket, so
   that a large group is tried around several hubs.
4. A pair's similarity is estimated from its registers by maximum likelihood, the set sizes
   being known; what is out of reach is dropped, the rest verified on the full sets.
5. Components of the links. In buckets whose members are still in different components, those
   outside the bucket's largest component are compared with all its members: in blocks, sketches
   first, full sets where the estimate allows a link, and only links leave a task. So no link that
   a shared bucket offers is lost; a pair at exactly 0.8 shares no bucket with probability 3e-6
   (42 bands of 6). This last comparison is outsiders times members, at some tens of nanoseconds.

Texts without words are linked with nothing; nulls are empty texts; rows with a null id take no
part and are their own class (null component, kept); rows that repeat an id are one node of the
graph, linked with whatever any of its texts is linked with: they share a component, each has its own
n_shingles, and equal ones are repeated in the result; an empty table gives an empty result. Only the id and text columns are read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected
from .shared import _GOLD, batch_of, bit_map, discard, id_text, mix64, shingle_hashes, slices, staged

REGISTERS, BAND_ROWS = 256, 6
OUT_BLOCK, IN_BLOCK = 32, 64
RATE, BASE, TOP = 20.0, 1.001, 65535  # fixed values: a, b and q + 1 of the sketch
MARGIN = 0.16  # estimates this far below the threshold (six standard errors) aren't verified
HUBS = 8  # a power of two
HOT_HUB = 4096

_MASKS = [int(x) >> 1 for x in mix64(np.arange(1, HUBS + 1, dtype=np.uint64) * _GOLD)]


# ------------------------------------------------------------------ sketches


def sketch(hashes: np.ndarray, offsets: np.ndarray, m: int = REGISTERS) -> np.ndarray:
    """Registers (rows x m, 16 bits) of the sets that lie end to end in `hashes`.

    All rows advance together: slice j of every shingle's points, until no point of a later
    slice can be below any register of its row.
    """
    n = len(offsets) - 1
    least = np.full(n * m, np.inf)
    owner = np.repeat(np.arange(n), np.diff(offsets))
    base = mix64(hashes)
    start = (base & np.uint64(m - 1)).astype(np.int64)
    stride = ((base >> np.uint64(20)) & np.uint64(m - 1)).astype(np.int64) | 1
    live = np.arange(len(hashes))
    for j in range(m):
        with np.errstate(over="ignore", divide="ignore"):
            u = (mix64(hashes[live] + np.uint64(j + 1) * _GOLD) >> np.uint64(11)) * 2.0**-53
            x = -np.log1p(-(j + u) / m) / RATE
        at = owner[live] * m + ((start[live] + j * stride[live]) & (m - 1))
        np.minimum.at(least, at, x)
        if j + 1 == m:
            break
        bound = -np.log1p(-(j + 1) / m) / RATE
        open_rows = least.reshape(n, m).max(axis=1) > bound
        live = live[open_rows[owner[live]]]
        if not len(live):
            break
    with np.errstate(divide="ignore"):
        k = np.floor(1.0 - np.log(least) / np.log(BASE))
    return np.clip(k, 0, TOP).astype(np.uint16).reshape(n, m)


def merged(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The sketch of the union."""
    return np.maximum(a, b)


def joint_estimate(k1: np.ndarray, k2: np.ndarray, n1: np.ndarray, n2: np.ndarray) -> np.ndarray:
    """Maximum-likelihood Jaccard similarity of sketch rows, given the set sizes."""
    above = (k1 > k2).sum(axis=1)
    below = (k1 < k2).sum(axis=1)
    equal = k1.shape[1] - above - below
    u = n1 / (n1 + n2)
    v = 1.0 - u
    scale = (BASE - 1) / BASE

    def p(x):
        return -np.log1p(-np.clip(x, 0, 1) * scale) / np.log(BASE)

    def likelihood(j):
        a, b = p(u - v * j), p(v - u * j)
        tiny = 1e-12
        return (
            above * np.log(np.maximum(a, tiny))
            + below * np.log(np.maximum(b, tiny))
            + equal * np.log(np.maximum(1 - a - b, tiny))
        )

    lo, hi = np.zeros_like(u), np.minimum(u / v, v / u)
    ratio = (np.sqrt(5) - 1) / 2
    for _ in range(40):  # golden section; the likelihood has one peak
        c, d = hi - ratio * (hi - lo), lo + ratio * (hi - lo)
        left = likelihood(c) >= likelihood(d)
        hi, lo = np.where(left, d, hi), np.where(left, lo, c)
    return (lo + hi) / 2


def band_keys(registers: np.ndarray, rows: int = BAND_ROWS) -> np.ndarray:
    """One 64-bit key per sketch and band of `rows` registers."""
    n, m = registers.shape
    bands = m // rows
    r = registers[:, : bands * rows].reshape(n, bands, rows).astype(np.uint64)
    with np.errstate(over="ignore"):
        h = np.broadcast_to(mix64(np.arange(1, bands + 1, dtype=np.uint64) * _GOLD), (n, bands))
        for i in range(rows):
            h = mix64(h * np.uint64(0xFF51AFD7ED558CCD) + r[:, :, i] + np.uint64(1))
    return h.view(np.int64)


# ------------------------------------------------------------------ stages


def scan(docs: DataFrame, size: int) -> DataFrame:
    """doc_id, n, f1, f2 (fingerprint), registers (null for an empty set) of every row."""
    schema = pa.schema(
        [("doc_id", pa.int64()), ("n", pa.int64()), ("f1", pa.int64()), ("f2", pa.int64()), ("registers", pa.binary())]
    )

    def run(batches):
        for part in slices(batches, 1 << 20):
            s, offsets = shingle_hashes(part.column(1), size)
            n = np.diff(offsets)
            with np.errstate(over="ignore"):
                sums = [
                    np.concatenate([[np.uint64(0)], np.cumsum(mix64(s ^ np.uint64(c)))]) for c in (0x5BD1E995, 0x9747B28C)
                ]
                f1, f2 = ((x[offsets[1:]] - x[offsets[:-1]]).view(np.int64) for x in sums)
            rows = sketch(s, offsets)
            yield batch_of(
                schema, part.column(0), n, f1, f2, [r.tobytes() if k else None for r, k in zip(rows, n.tolist())]
            )

    return docs.mapInArrow(run, "doc_id long, n long, f1 long, f2 long, registers binary")


def banded(classes: DataFrame) -> DataFrame:
    """key, id: a row for each class and band."""
    schema = pa.schema([("key", pa.int64()), ("id", pa.int64())])

    def run(batches):
        for part in slices(batches, 1 << 20):
            regs = np.frombuffer(b"".join(part.column(1).to_pylist()), dtype=np.uint16).reshape(part.num_rows, -1)
            keys = band_keys(regs)
            ids = np.repeat(part.column(0).to_numpy(zero_copy_only=False), keys.shape[1])
            yield batch_of(schema, keys.reshape(-1), ids)

    return classes.select("id", "registers").mapInArrow(run, "key long, id long")


def full_sets(docs: DataFrame, ids: DataFrame, pairs: DataFrame, size: int) -> DataFrame:
    """id, shingles (sorted 64-bit hashes), registers of the documents named in `ids`; is_a, is_b: whether one
    may be the first or the second of some of the `pairs`, so that `verified` moves it for those sides only.

    A bit map of the ids lets a scan pass over the other texts without moving any; the few that
    pass by chance find no pair later. Too many ids for the map: an equi-join with the texts.
    """
    schema = pa.schema(
        [("id", pa.int64()), ("shingles", pa.binary()), ("registers", pa.binary()), ("is_a", pa.bool_()), ("is_b", pa.bool_())]
    )
    named = bit_map(ids, F.xxhash64("id"))
    sides = [bit_map(pairs.select(k).distinct(), F.xxhash64(k)) for k in ("a", "b")]
    if named is None:
        rows = docs.join(ids.select(F.col("id").alias("doc_id")), "doc_id", "left_semi").dropDuplicates(["doc_id", "text"])
    else:
        rows = docs.where("doc_id IS NOT NULL")
    rows = rows.select("doc_id", "text", F.xxhash64("doc_id").alias("hash"))
    shipped = docs.sparkSession.sparkContext.broadcast((named, *sides))

    def run(batches):
        named, *sides = shipped.value
        for part in slices(batches, 1 << 20):
            if named is not None:
                part = part.filter(pa.array(named.has(part.column(2).to_numpy())))
                if not part.num_rows:
                    continue
            hashes = part.column(2).to_numpy()
            is_a, is_b = (np.ones(part.num_rows, dtype=bool) if m is None else m.has(hashes) for m in sides)
            s, offsets = shingle_hashes(part.column(1), size)
            regs = sketch(s, offsets)
            cut = offsets.tolist()
            yield batch_of(
                schema,
                part.column(0),
                [s[a:b].tobytes() for a, b in zip(cut[:-1], cut[1:])],
                [r.tobytes() for r in regs],
                is_a,
                is_b,
            )

    return rows.mapInArrow(run, "id long, shingles binary, registers binary, is_a boolean, is_b boolean")


def blocks(rows: DataFrame, sets: DataFrame, most: int, name: str) -> DataFrame:
    """grp, <name>: arrays of about `most` (id, shingles, registers) each, dealt by a hash."""
    chunks = rows.groupBy("grp").agg(F.ceil(F.count("*") / most).cast("int").alias("chunks"))
    dealt = rows.join(chunks, "grp").select("grp", "id", F.pmod(F.xxhash64("id"), F.col("chunks")).alias("chunk"))
    member = F.struct("id", "shingles", "registers")
    return dealt.join(sets, "id").groupBy("grp", "chunk").agg(F.collect_list(member).alias(name)).drop("chunk")


def block_links(outside: DataFrame, members: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) between rows of `outside` and of `members` (grp, id) of one group."""
    pairs = blocks(outside, sets, OUT_BLOCK, "out").join(blocks(members, sets, IN_BLOCK, "all"), "grp").select("out", "all")
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def unpacked(rows):
        regs = np.frombuffer(b"".join(r["registers"] for r in rows), dtype=np.uint16).reshape(len(rows), -1)
        return [r["id"] for r in rows], [np.frombuffer(r["shingles"], dtype=np.uint64) for r in rows], regs

    def run(batches):
        for part in slices(batches):
            found = set()
            for row in part.to_pylist():
                ids, sets_a, regs_a = unpacked(row["out"])
                others, sets_b, regs_b = unpacked(row["all"])
                n2 = np.array([len(x) for x in sets_b], dtype=float)
                for i, x, k in zip(ids, sets_a, regs_a):
                    fits = (100 * np.minimum(len(x), n2) >= percent * np.maximum(len(x), n2)) & (
                        (regs_b == k).sum(axis=1) >= (percent / 100 - MARGIN) * len(k)
                    )
                    for j in np.flatnonzero(fits):
                        y = sets_b[j]
                        if others[j] != i:
                            common = len(np.intersect1d(x, y, assume_unique=True))
                            if 100 * common >= percent * (len(x) + len(y) - common):
                                found.add((min(i, others[j]), max(i, others[j])))
            a, b = zip(*sorted(found)) if found else ((), ())
            yield batch_of(schema, list(a), list(b))

    return pairs.mapInArrow(run, "a long, b long").distinct()


def verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets reach `percent` of Jaccard similarity.

    Hubs with many pairs are salted: their set is copied once for every HOT_HUB pairs.
    """
    hot = (
        pairs.groupBy("a").agg(F.count("*").alias("k")).where(F.col("k") > HOT_HUB)
        .select("a", F.ceil(F.col("k") / HOT_HUB).cast("int").alias("copies"))
    )
    salted = pairs.join(hot, "a", "left").select(
        "a", "b", F.when(F.col("copies").isNull(), F.lit(0)).otherwise(F.pmod(F.xxhash64("b"), F.col("copies"))).cast("int").alias("salt")
    )
    left = (
        sets.where("is_a").select(F.col("id").alias("a"), F.col("shingles").alias("sa"), F.col("registers").alias("ra"))
        .join(hot, "a", "left")
        .withColumn("salt", F.explode(F.sequence(F.lit(0), F.coalesce("copies", F.lit(1)) - 1)))
        .drop("copies")
    )
    right = sets.where("is_b").select(F.col("id").alias("b"), F.col("shingles").alias("sb"), F.col("registers").alias("rb"))
    both = salted.join(right, "b").join(left, ["a", "salt"]).select("a", "b", "sa", "sb", "ra", "rb")
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def run(batches):
        for part in slices(batches):
            sa, sb, ra, rb = (part.column(k).to_pylist() for k in range(2, 6))
            n1 = np.array([len(x) // 8 for x in sa], dtype=float)
            n2 = np.array([len(x) // 8 for x in sb], dtype=float)
            k1, k2 = (np.frombuffer(b"".join(r), dtype=np.uint16).reshape(len(r), -1) for r in (ra, rb))
            near = joint_estimate(k1, k2, n1, n2) >= percent / 100 - MARGIN
            keep = np.zeros(part.num_rows, dtype=bool)
            for i in np.flatnonzero(near):
                x, y = np.frombuffer(sa[i], dtype=np.uint64), np.frombuffer(sb[i], dtype=np.uint64)
                if 100 * min(len(x), len(y)) < percent * max(len(x), len(y)):
                    continue
                common = len(np.intersect1d(x, y, assume_unique=True))
                keep[i] = 100 * common >= percent * (len(x) + len(y) - common)
            mask = pa.array(keep)
            yield batch_of(schema, part.column(0).filter(mask), part.column(1).filter(mask))

    return both.mapInArrow(run, "a long, b long").distinct()


def ordered(a, b) -> list:
    return [F.least(a, b).alias("a"), F.greatest(a, b).alias("b")]


def near_duplicates(
    docs: DataFrame, size: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every row: components of the graph that links
    documents whose sets of `size`-word shingles have at least `percent` % Jaccard similarity."""
    docs = id_text(docs, id_col, text_col)
    rows = staged(scan(docs, size), "sketches")
    classes = staged(
        rows.where("n > 0 AND doc_id IS NOT NULL")
        .groupBy("f1", "f2", "n")
        .agg(F.min("doc_id").alias("id"), F.first("registers").alias("registers")),
        "classes",
    )
    rows, sketched = staged(rows.select("doc_id", "n", "f1", "f2"), "rows"), rows
    discard(sketched)  # registers are most of the table, and only the classes' are needed from here
    bands = banded(classes)
    masks = F.array(*[F.lit(x) for x in _MASKS])
    mask = F.get(masks, F.col("key").bitwiseAND(F.lit(HUBS - 1)).cast("int"))
    buckets = (
        bands.groupBy("key")
        .agg(F.count("*").alias("k"), F.min(F.col("id").bitwiseXOR(mask)).alias("least"))
        .where("k > 1")
        .select("key", F.col("least").bitwiseXOR(mask).alias("hub"))
    )
    members = staged(bands.join(buckets, "key"), "members")
    classes, sketched = staged(classes.drop("registers"), "named"), classes
    discard(sketched)
    pairs = staged(members.where("id <> hub").select(*ordered("id", "hub")).distinct(), "pairs")
    sets = staged(full_sets(docs, members.select("id").distinct(), pairs, size), "sets")
    links = verified(pairs, sets, percent)
    again = rows.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.count("*").alias("k")).where("k > 1").select("doc_id")
    again = staged(again, "repeated")
    repeated = not again.isEmpty()
    if repeated:  # the texts of one id belong together
        texts = rows.where("n > 0").join(again, "doc_id").join(classes, ["f1", "f2", "n"])
        links = links.union(texts.groupBy("doc_id", "id").agg(F.lit(1)).select(*ordered("doc_id", "id")))
    links = staged(links, "links")
    component = staged(connected(links), "components")

    placed = members.join(component, "id", "left").select("key", "id", F.coalesce("component", "id").alias("component"))
    # A bucket of two has no pair but the one around its hub.
    split = (
        placed.groupBy("key", "component")
        .agg(F.count("*").alias("k"))
        .groupBy("key")
        .agg(F.sum("k").alias("n"), F.max_by("component", F.struct("k", "component")).alias("grp"), F.count("*").alias("parts"))
        .where("parts > 1 AND n > 2")
        .select("key", "grp")
    )
    here = staged(placed.join(split, "key").select("grp", "id", (F.col("component") != F.col("grp")).alias("outside")).distinct(), "split")
    outside = here.where("outside").select("grp", "id")
    more = staged(block_links(outside, here.select("grp", "id").distinct(), sets, percent), "links")
    if not more.isEmpty():
        component = staged(connected(links.union(more)), "components")
    for done in (members, pairs, sets, here):
        discard(done)
    smallest = classes.select("f1", "f2", "n", "id").join(component, "id", "left").select(
        "f1", "f2", "n", F.coalesce("component", "id").alias("component_id")
    )
    found = rows.select("doc_id", "n", "f1", "f2").join(smallest, ["f1", "f2", "n"], "left")
    component_id = F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id"))
    if repeated:  # an id whose only text is a copy has its node in no class; an empty text has none either
        nodes = component.select(F.col("id").alias("doc_id"), F.col("component").alias("own")).join(again, "doc_id", "left_semi")
        found = found.join(nodes, "doc_id", "left")
        component_id = F.when(F.col("doc_id").isNotNull(), F.coalesce("own", "component_id", "doc_id"))
    return found.select(
        "doc_id",
        F.col("n").alias("n_shingles"),
        component_id.alias("component_id"),
        F.coalesce(F.col("doc_id") == component_id, F.lit(True)).alias("kept"),
    )
