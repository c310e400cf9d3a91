"""SimHash near-duplicates with bit-sliced comparison.

Fingerprints are made next to the scan; after that only (fingerprint, smallest doc_id) travels. Equal
fingerprints are merged first, so a group of copies is one row however large it is. Two fingerprints within
``radius`` of each other agree on all bits of at least ``clean`` of ``radius + clean`` bands (pigeonhole), so a row for
each choice of clean bands brings every such pair into one bucket; larger tables take more clean bands, so that keys are
longer and buckets stay small. A bucket over ``block`` rows is cut into
pairs of blocks, which are groups of their own. Inside a group the bit planes are stored vertically: 64 distances advance by one bitwise
operation in carry-save counters, and a tile is abandoned once all of its distances exceed the radius. A group
returns a spanning forest of what it linked, never all pairs. Components are found by alternating star
operations on checkpointed links.

Defined results: null or wordless texts have the fingerprint zero and link like others; texts of any length are read whole (a
task holds one, its words and eight bytes for each shingle); repeated rows are kept by ``near_duplicates``; a component of
which all ids are null has a null id; ties of ids fall by the text's hash; an empty table gives no rows; other columns, of any
name, are ignored or kept as they are.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import arrow_schema, checkpoint, chunks, dense, join_hot, text_bytes

RADIUS = 4
SHINGLE_WORDS = 4
SEED = 42
#: Rows of a bucket that are compared as one block, and the most rows that a bucket should have on average.
BLOCK, BUCKET = 2048, 512

#: Near copies of a stage on word shingles: five words, Jaccard similarity. Texts that agree on all minima of a band may be near
#: copies (of similarity 0.8: 0.9996 of the pairs); their fingerprints are compared within WIDE bits (0.8 is 10 bits on
#: average) and their shingles exactly.
SIMILAR, SIMILAR_WORDS, WIDE = 0.8, 5, 24
BANDS, MINIMA, SIMILAR_BLOCK = 20, 5, 512


def shingle_hashes(body: bytes | None, words: int) -> np.ndarray:
    """(n, 8) bytes of the hashes of a text's shingles, repeated ones too; a short text is one shingle."""
    from xxhash import xxh64_digest

    tokens = body.lower().split() if body else ()
    if not tokens:
        return np.zeros((0, 8), dtype="uint8")
    grams = map(b" ".join, zip(*[tokens[k:] for k in range(words)])) if len(tokens) > words else (b" ".join(tokens),)
    return np.frombuffer(b"".join([xxh64_digest(g, SEED) for g in grams]), dtype="uint8").reshape(-1, 8)


def fingerprint(raw: np.ndarray) -> int:
    """A bit is set if more than half of the hashes have it."""
    set_bits = np.zeros(64, dtype="int64")
    for at in range(0, len(raw), 4096):
        set_bits += np.unpackbits(raw[at : at + 4096], axis=1).sum(axis=0, dtype="uint16")
    return int("".join("1" if 2 * x > len(raw) else "0" for x in set_bits.tolist()), 2)


def fingerprints(docs: DataFrame, words: int = SHINGLE_WORDS, id_col: str = "doc_id", text_col: str = "text", row: Column | None = None) -> DataFrame:
    """(doc_id, fp long[, row long]): a bit is set if more than half of the shingle hashes have it."""
    schema = "doc_id long, fp long" + (", row long" if row is not None else "")
    arrow = arrow_schema(docs.sparkSession, schema)

    def run(batches):
        for part in chunks(batches):
            out = np.zeros(part.num_rows, dtype="uint64")
            for i, body in enumerate(part.column(1).to_pylist()):
                raw = shingle_hashes(body, words)
                if len(raw):
                    out[i] = fingerprint(raw)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(out.view("int64")), *part.columns[2:]], schema=arrow)

    return text_bytes(docs, id_col, text_col, *([] if row is None else [row.alias("row")])).mapInArrow(run, schema)


def planes_of(values: np.ndarray) -> np.ndarray:
    """(64, ceil(n/64)) words: bit j of word w of plane k is bit k of value 64*w+j."""
    n = len(values)
    bits = np.unpackbits(np.ascontiguousarray(values, dtype="<u8").view("uint8").reshape(n, 8), axis=1, bitorder="little")
    padded = np.zeros((64, -(-n // 64) * 64), dtype="uint8")
    padded[:, :n] = bits.T
    return np.packbits(padded, axis=1, bitorder="little").view("<u8")


def close_pairs(queries: np.ndarray, planes: np.ndarray, n: int, radius: int = RADIUS, tile: int = 128):
    """Yield (query indices, value indices) of distances up to ``radius`` by vertical carry-save counters.

    Three counter planes and a sticky overflow plane hold 64 distances a word. After every eighth bit plane a
    tile is abandoned if all its distances are over the radius already.
    """
    full = np.uint64(0xFFFFFFFFFFFFFFFF)
    width = planes.shape[1]
    valid = np.full(width, full)
    if n % 64:
        valid[-1] = np.uint64((1 << (n % 64)) - 1)
    levels = max(1, radius.bit_length())
    for at in range(0, len(queries), tile):
        q = queries[at : at + tile]
        counters = [np.zeros((len(q), width), dtype="uint64") for _ in range(levels)]
        over = np.zeros((len(q), width), dtype="uint64")
        dead = False
        for k in range(64):
            flip = np.where((q >> np.uint64(k)) & np.uint64(1), full, np.uint64(0))[:, None]
            carry = planes[k][None, :] ^ flip
            for c in counters:
                kept = c & carry
                c ^= carry
                carry = kept
            over |= carry
            if k % 8 == 7 and k < 63:
                if not ((~(over | _above(counters, radius))) & valid).any():
                    dead = True
                    break
        if dead:
            continue
        near = ~(over | _above(counters, radius)) & valid
        rows, words = np.nonzero(near)
        if len(rows):
            bits = np.unpackbits(near[rows, words].view("uint8").reshape(-1, 8), axis=1, bitorder="little")
            hit, bit = np.nonzero(bits)
            yield at + rows[hit], words[hit] * 64 + bit


def _above(counters: list[np.ndarray], radius: int) -> np.ndarray:
    """Bitwise: the vertical counter is greater than the radius."""
    greater = np.zeros_like(counters[0])
    equal = ~greater
    for level in range(len(counters) - 1, -1, -1):
        if radius >> level & 1:
            equal &= counters[level]
        else:
            greater |= equal & counters[level]
            equal &= ~counters[level]
    return greater


def forest(values: np.ndarray, split: int | None = None, radius: int = RADIUS) -> tuple[np.ndarray, np.ndarray]:
    """Links of a spanning forest of the pairs within the radius.

    With ``split`` only pairs between values[:split] and values[split:] are compared. Labels are kept in an array,
    so a tile in which all hits are linked already costs no Python step; the first tiles are small, so that one of
    them gathers a dense group.
    """
    n = len(values)
    queries, target, base = (values, values, 0) if split is None else (values[:split], values[split:], split)
    planes, label = planes_of(target), np.arange(n)
    left: list[int] = []
    right: list[int] = []
    at, width = 0, 1
    while at < len(queries):
        for i, j in close_pairs(queries[at : at + width], planes, len(target), radius, width):
            i, j = i + at, j + base
            new = label[i] != label[j]
            if not new.any():
                continue
            i, j = i[new], j[new]
            _, first = np.unique(label[i] * n + label[j], return_index=True)
            root = np.arange(n)

            def find(x: int) -> int:
                while root[x] != x:
                    root[x] = root[root[x]]
                    x = root[x]
                return x

            for x, y in zip(i[first].tolist(), j[first].tolist()):
                p, q = find(label[x]), find(label[y])
                if p != q:
                    root[max(p, q)] = min(p, q)
                    left.append(x)
                    right.append(y)
            while (root[root] != root).any():
                root = root[root]
            label = root[label]
        at, width = at + width, min(128, width * 4)
    return values[left], values[right]


def band_masks(bands: int, clean: int) -> list[int]:
    cuts = [64 * i // bands for i in range(bands + 1)]
    parts = [sum(1 << b for b in range(lo, hi)) for lo, hi in zip(cuts, cuts[1:])]
    return [sum(c) for c in combinations(parts, clean)]


def _group_links(group: np.ndarray, fp: np.ndarray, first: np.ndarray, radius: int) -> tuple[list, list]:
    """Links inside runs of equal ``group`` numbers; ``first`` tells the first block of a pair of blocks (-1: one block)."""
    starts = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    sizes = np.diff(np.r_[starts, len(group)])
    a, b = [], []
    large = (sizes >= 24) | (first[starts] >= 0)
    for s, n in zip(starts[large].tolist(), sizes[large].tolist()):
        own, side = fp[s : s + n], first[s : s + n]
        if side[0] >= 0:
            own = np.concatenate([own[side == 1], own[side == 0]])
            x, y = forest(own, int((side == 1).sum()), radius)
        else:
            x, y = forest(own, None, radius)
        a.append(x)
        b.append(y)
    # groups that do not fill a word: the d-th next row, for all groups at once
    small = np.repeat(~large, sizes)
    g, f = group[small], fp[small]
    for d in range(1, int(sizes[~large].max(initial=1))):
        same = g[d:] == g[:-d]
        if not same.any():
            break
        x, y = f[:-d][same], f[d:][same]
        near = np.bitwise_count(x ^ y) <= radius
        a.append(x[near])
        b.append(y[near])
    return a, b


def clean_bands(rows: int, radius: int = RADIUS) -> int:
    """How many bands, of as many and ``radius`` more, a key has: two, three or four, so that buckets have BUCKET rows at most on average."""
    return next((c for c in (2, 3) if rows <= BUCKET << 64 * c // (radius + c)), 4)


def links(distinct: DataFrame, radius: int = RADIUS, block: int = BLOCK, clean: int | None = None) -> DataFrame:
    """(a, b): links whose components are those of all pairs of ``distinct.fp`` within the radius."""
    clean = clean or clean_bands(distinct.count(), radius)
    masks = band_masks(radius + clean, clean)
    signed = lambda m: m - (1 << 64) if m >> 63 else m
    keyed = distinct.select("fp", F.posexplode(F.array(*[F.col("fp").bitwiseAND(F.lit(signed(m))) for m in masks])).alias("band", "part"))
    # a bucket over ``block`` rows becomes pairs of blocks, each a group of its own
    hot = keyed.groupBy("band", "part").agg(F.count("*").alias("size")).where(F.col("size") > block)
    cells = F.coalesce(F.ceil(F.col("size") / block), F.lit(1)).cast("int")
    own = F.pmod(F.xxhash64("fp"), cells.cast("bigint")).cast("int")
    pairs = F.transform(F.sequence(F.lit(0), cells - 1), lambda c: F.struct(F.least(own, c).alias("lo"), F.greatest(own, c).alias("hi")))
    dealt = (
        keyed.join(hot, ["band", "part"], "left")
        .select("band", "part", "fp", own.alias("cell"), F.explode(pairs).alias("pair"))
        .select("band", "part", "pair.lo", "pair.hi", F.when(F.col("pair.lo") == F.col("pair.hi"), -1).otherwise((F.col("cell") == F.col("pair.lo")).cast("int")).alias("first"), "fp")
        .repartition("band", "part", "lo", "hi")
        .sortWithinPartitions("band", "part", "lo", "hi")
    )
    schema = "a long, b long"
    arrow = arrow_schema(distinct.sparkSession, schema)

    def run(batches):
        rest = None
        for batch in batches:
            if not batch.num_rows:
                continue
            got = [batch.column(k).to_numpy(zero_copy_only=False).astype("int64") for k in range(6)]
            rows = got if rest is None else [np.concatenate(x) for x in zip(rest, got)]
            key = np.stack(rows[:4])
            change = np.flatnonzero((key[:, 1:] != key[:, :-1]).any(axis=0)) + 1
            cut = int(change[-1]) if len(change) else 0  # the last group may go on in the next batch
            rest = [x[cut:] for x in rows]
            if cut:
                yield out([x[:cut] for x in rows])
        if rest is not None and len(rest[0]):
            yield out(rest)

    def out(rows):
        key = np.stack(rows[:4])
        group = np.r_[0, np.cumsum((key[:, 1:] != key[:, :-1]).any(axis=0))]
        a, b = _group_links(group, rows[5].view("uint64"), rows[4], radius)
        a, b = (np.concatenate([np.zeros(0, "uint64"), *x]).view("int64") for x in (a, b))
        return pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], schema=arrow)

    return dealt.mapInArrow(run, schema)


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root): root is the smallest node reachable, for nodes that have links. Alternates large and small stars."""
    both = checkpoint(edges.where("a <> b").select(F.greatest("a", "b").alias("v"), F.least("a", "b").alias("u")).distinct())
    rows, last = both.count(), None
    both = dense(both, rows)
    for _ in range(max_rounds):
        # large star: larger neighbours go to the smallest of the neighbourhood
        near = both.select("v", "u").union(both.select(F.col("u").alias("v"), F.col("v").alias("u")))
        larger = F.count_if(F.col("u") > F.col("v")).alias("n")
        least = checkpoint(dense(near.groupBy("v").agg(F.least(F.min("u"), F.col("v")).alias("m"), larger).where("n > 0"), rows))
        large = join_hot(both.select(F.col("u").alias("v"), F.col("v").alias("u")), least, ["v"], "n").select(F.col("u").alias("v"), F.col("m").alias("u"))
        large = checkpoint(dense(large.distinct(), rows))
        # small star: smaller neighbours and the node itself go to the smallest
        low = checkpoint(dense(large.groupBy("v").agg(F.min("u").alias("m"), F.count("*").alias("n")), rows))
        several = join_hot(large, low.where("n > 1"), ["v"], "n").select(F.col("u").alias("v"), F.col("m").alias("u")).where("v <> u")
        both = checkpoint(dense(several.union(low.select("v", F.col("m").alias("u"))).distinct(), rows))
        now = both.agg(F.count("*"), F.sum(F.xxhash64("v", "u").cast("decimal(38,0)"))).first()
        if tuple(now) == last:
            break
        last, rows = tuple(now), now[0]
    else:
        raise RuntimeError("components did not settle")
    return both.select(F.col("v").alias("node"), F.col("u").alias("root"))


def near_duplicates(docs: DataFrame, radius: int = RADIUS, words: int = SHINGLE_WORDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id: the smallest doc_id reachable by links."""
    marked = checkpoint(fingerprints(docs, words, id_col, text_col))
    classes = checkpoint(marked.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count("*").alias("n")))
    roots = checkpoint(components(links(classes.select("fp"), radius)))
    # only classes that have links share a root; all others are their own component
    linked = checkpoint(roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct()).withColumnRenamed("node", "fp").join(classes, "fp"))
    least = checkpoint(linked.groupBy("root").agg(F.min("least").alias("component_id"), F.count("*").alias("classes")))
    named = join_hot(linked.select("root", "fp", "n"), least, ["root"], "classes").select("fp", "component_id", "n")
    alone = classes.join(linked.select("fp"), "fp", "left_anti").select("fp", F.col("least").alias("component_id"), "n")
    ids = join_hot(marked, checkpoint(named.unionByName(alone)), ["fp"], "n")
    return ids.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


#: Stands for a null doc_id where rows are matched.
UNNAMED = -(1 << 63)


def _named(docs: DataFrame) -> Column:
    return F.coalesce(F.col("doc_id").cast("bigint"), F.lit(UNNAMED))


def keep_one(docs: DataFrame, radius: int = RADIUS, words: int = SHINGLE_WORDS) -> DataFrame:
    """docs with one row of each component, the one with the smallest doc_id; of repeated rows one stays.

    Rows are matched by doc_id and a hash of the text, so only the hashes of the kept rows travel to the texts.
    """
    marked = checkpoint(fingerprints(docs.withColumn("doc_id", _named(docs)), words, row=F.xxhash64("text")))
    classes = checkpoint(marked.groupBy("fp").agg(_least()))
    roots = components(links(classes.select("fp"), radius))
    tied = classes.join(roots, classes.fp == roots.node, "left").select("least", F.coalesce("root", "fp").alias("root"))
    return _rows_kept(docs, marked, tied)


def _least() -> Column:
    """The row of the smallest doc_id, unnamed ones last."""
    return F.min(F.struct((F.col("doc_id") == UNNAMED).alias("unnamed"), "doc_id", "row")).alias("least")


def _rows_kept(docs: DataFrame, marked: DataFrame, tied: DataFrame) -> DataFrame:
    """The rows of docs that are the least of tied's roots, each once."""
    again = marked.groupBy("doc_id", "row").agg(F.count("*").alias("n")).where("n > 1").select("doc_id", "row", F.lit(True).alias("again"))
    kept = tied.groupBy("root").agg(F.min("least").alias("least")).select("least.doc_id", "least.row").join(again, ["doc_id", "row"], "left")
    found = docs.select(F.struct(*docs.columns).alias("doc"), _named(docs).alias("doc_id"), F.xxhash64("text").alias("row")).join(kept, ["doc_id", "row"])
    once = found.where("again is null").select("doc")
    first = found.where("again").groupBy("doc_id", "row").agg(F.first("doc").alias("doc")).select("doc")
    return once.unionByName(first).select(*[F.col(f"doc.`{c}`").alias(c) for c in docs.columns])


def sketches(docs: DataFrame, words: int = SIMILAR_WORDS) -> DataFrame:
    """(doc_id, row: a hash of the text, same, fp, bands): a hash of the set of shingles, the fingerprint, and a hash of the minima of each band."""
    schema = "doc_id long, row long, same long, fp long, bands array<long>"
    arrow = arrow_schema(docs.sparkSession, schema)

    def run(batches):
        from xxhash import xxh64_intdigest

        rng = np.random.default_rng(SEED)
        factors, terms = (rng.integers(0, 1 << 64, BANDS * MINIMA, dtype="uint64") for _ in range(2))
        factors |= np.uint64(1)
        for part in chunks(batches):
            same, fp = np.zeros((2, part.num_rows), dtype="uint64")
            bands = np.zeros((part.num_rows, BANDS), dtype="uint64")
            for i, body in enumerate(part.column(1).to_pylist()):
                raw = shingle_hashes(body, words)
                if len(raw):
                    fp[i] = fingerprint(raw)
                own = np.unique(raw.view("uint64"))
                same[i] = xxh64_intdigest(own.tobytes(), SEED)
                least = np.full(BANDS * MINIMA, 0xFFFFFFFFFFFFFFFF, dtype="uint64")
                for at in range(0, len(own), 512):
                    np.minimum(least, (own[at : at + 512, None] * factors + terms).min(axis=0), out=least)
                bands[i] = [xxh64_intdigest(x.tobytes(), k) for k, x in enumerate(least.reshape(BANDS, MINIMA))]
            flat = pa.ListArray.from_arrays(pa.array(range(0, BANDS * part.num_rows + 1, BANDS), pa.int32()), pa.array(bands.ravel().view("int64")))
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(same.view("int64")), pa.array(fp.view("int64")), flat.cast(arrow.types[4])], schema=arrow)

    return text_bytes(docs.withColumn("doc_id", _named(docs)), "doc_id", "text", F.xxhash64("text").alias("row")).mapInArrow(run, schema)


def similar_forest(sets: list[np.ndarray], fp: np.ndarray, split: int | None = None, similarity: float = SIMILAR) -> list[tuple[int, int]]:
    """Links of a spanning forest of the pairs whose sets have the similarity; with ``split`` only pairs across it."""
    queries, target, base = (fp, fp, 0) if split is None else (fp[:split], fp[split:], split)
    root, found = list(range(len(fp))), []

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for i, j in close_pairs(queries, planes_of(target), len(target), WIDE):
        for x, y in zip(i.tolist(), (j + base).tolist()):
            p, q = find(x), find(y)
            if p == q:
                continue
            a, b = len(sets[x]), len(sets[y])
            if min(a, b) < similarity * max(a, b):
                continue
            common = len(np.intersect1d(sets[x], sets[y], assume_unique=True))
            if common >= similarity * (a + b - common):
                root[max(p, q)] = min(p, q)
                found.append((x, y))
    return found


def similar_links(docs: DataFrame, classes: DataFrame, words: int = SIMILAR_WORDS, block: int = SIMILAR_BLOCK) -> DataFrame:
    """(a, b) of classes' ``same``: links whose components are those of the similar pairs that share a band.

    Texts that share bands, over any number of steps, make a group; each text that is in one is sent to it once, or, if
    the group has more than ``block``, to pairs of blocks. Classes have same, doc_id, row, n (rows of the table that
    have both), fp, bands.
    """
    keyed = classes.select("same", F.explode("bands").alias("band"))
    shared = checkpoint(keyed.groupBy("band").agg(F.min("same").alias("b"), F.count("*").alias("n")).where("n > 1"))
    groups = checkpoint(components(join_hot(keyed, shared, ["band"], "n").select(F.col("same").alias("a"), "b")))
    groups = groups.unionByName(groups.select(F.col("root").alias("node"), "root").distinct())
    sizes = groups.groupBy("root").agg(F.count("*").alias("size"))
    cells = F.ceil(F.col("size") / block).cast("int")
    own = F.pmod(F.xxhash64("node"), cells.cast("bigint")).cast("int")
    pairs = F.transform(F.sequence(F.lit(0), cells - 1), lambda c: F.struct(F.least(own, c).alias("lo"), F.greatest(own, c).alias("hi")))
    sized = join_hot(groups, checkpoint(sizes), ["root"], "size")
    members = sized.join(classes, F.col("node") == F.col("same")).select("root", own.alias("cell"), pairs.alias("pairs"), "same", "doc_id", "row", "n", "fp")
    texts = docs.select(_named(docs).alias("doc_id"), F.xxhash64("text").alias("row"), F.col("text").cast("binary").alias("body"))
    held = members.join(texts, ["doc_id", "row"])
    # of repeated rows one is sent
    held = held.where("n = 1").unionByName(held.where("n > 1").groupBy("same").agg(*[F.first(c).alias(c) for c in held.columns if c != "same"]).select(*held.columns))
    dealt = held.select("root", "cell", F.explode("pairs").alias("pair"), "same", "fp", "body")
    dealt = dealt.select("root", "pair.lo", "pair.hi", (F.col("cell") == F.col("pair.lo")).alias("first"), "same", "fp", "body")
    schema = "a long, b long"
    arrow = arrow_schema(docs.sparkSession, schema)

    def run(table):
        same, at = np.unique(table.column("same").to_numpy(), return_index=True)  # repeated rows have one text
        table = table.take(pa.array(at))
        first = table.column("first").to_numpy(zero_copy_only=False).astype(bool)
        order, split = np.arange(len(same)), None
        if table.column("lo")[0].as_py() != table.column("hi")[0].as_py():
            order, split = np.argsort(~first, kind="stable"), int(first.sum())
        bodies = table.column("body").take(pa.array(order)).to_pylist()
        sets = [np.unique(shingle_hashes(b, words).view("uint64")) for b in bodies]
        found = similar_forest(sets, table.column("fp").to_numpy()[order].view("uint64"), split)
        ends = same[order[np.array(found, dtype="int64").reshape(-1, 2)]]
        return pa.Table.from_arrays([pa.array(ends[:, 0]), pa.array(ends[:, 1])], schema=arrow)

    return dealt.groupBy("root", "lo", "hi").applyInArrow(run, schema)


def keep_one_similar(docs: DataFrame, words: int = SIMILAR_WORDS) -> DataFrame:
    """docs with one row, the one with the smallest doc_id, of each component of texts whose sets of shingles are SIMILAR."""
    marked = checkpoint(sketches(docs, words))
    rows = marked.groupBy("same", "doc_id", "row").agg(F.count("*").alias("n"), F.first("fp").alias("fp"), F.first("bands").alias("bands"))
    least = F.min(F.struct((F.col("doc_id") == UNNAMED).alias("unnamed"), "doc_id", "row", "n")).alias("least")
    classes = checkpoint(rows.groupBy("same").agg(least, F.first("fp").alias("fp"), F.first("bands").alias("bands")))
    roots = components(similar_links(docs, classes.select("same", "least.doc_id", "least.row", "least.n", "fp", "bands"), words))
    tied = classes.join(roots, classes.same == roots.node, "left").select("least", F.coalesce("root", "same").alias("root"))
    return _rows_kept(docs, marked, tied)
