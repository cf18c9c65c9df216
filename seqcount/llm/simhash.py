"""SimHash near-dedup by multi-index hashing with small Hamming balls."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqcount.llm.common import BROADCAST_ROWS, checkpointed, discard, few, join_by_weight, text_fingerprint, without_rows, written
from seqcount.llm.shingles import BITS, bit_counts, majority, parts_of

SHINGLE_WORDS, SEGMENTS, RADIUS = 3, 2, 2
#: Fingerprints under one key of a table beyond which the key is split by the bits that it leaves open.
KEY_ROWS = 64
#: Near copies that are dropped: shingles of so many words, with this Jaccard similarity or more.
COPY_WORDS, COPY_SIMILARITY = 5, 0.8
#: Keys of a sketch, and shingles that each is made of: at similarity 0.8 all but 2 pairs in 1,000 share a key.
SKETCH_PARTS, SKETCH_LEAST = 12, 4
#: Shingles of the rows of one key that are compared with one another at once.
CELL_SHINGLES = 1 << 16
_ODD = np.uint64(0x9E3779B97F4A7C15)


def fingerprint_array(texts: pa.Array, words: int = SHINGLE_WORDS) -> np.ndarray:
    """64 bits of each text: each is set if it's set in over half of the shingles' XXH64; 0 for a text without words."""
    out, held = np.zeros(len(texts), np.int64), None
    for part in parts_of(texts, words):
        hashes, before = part.shingles(words)
        held = _added(held, hashes, before)
        if not part.more:
            out[part.first : part.first + part.texts] = majority(*held)
            held = None
    return out


def _added(held: tuple | None, hashes: np.ndarray, before: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(set bits, hashes) of each text, with what earlier blocks of a long text had."""
    ones, n = bit_counts(hashes, before), np.diff(before)
    return (ones + held[0], n + held[1]) if held else (ones, n)


def fingerprint(text: str | None, words: int = SHINGLE_WORDS) -> int:
    """The fingerprint of one text, as a signed number."""
    return int(fingerprint_array(pa.array([text], pa.string()), words)[0])


def fingerprints(docs: DataFrame, id_col: str, text_col: str, words: int = SHINGLE_WORDS) -> DataFrame:
    """(rid, fp, tfp) of every row, materialised; tfp names the text for a later filter."""
    rows = docs.select(F.col(id_col).cast("long").alias("rid"), F.col(text_col).cast("string").alias("text"), text_fingerprint(text_col).alias("tfp"))

    def run(batches):
        for batch in batches:
            fp = pa.array(fingerprint_array(batch.column(1), words))
            yield pa.RecordBatch.from_arrays([batch.column(0), fp, batch.column(2)], names=["rid", "fp", "tfp"])

    return checkpointed(rows.mapInArrow(run, "rid long, fp long, tfp long"))


# --- links within a radius: tables keyed by segments, probed with Hamming balls


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def segments_of(width: int, parts: int) -> list[tuple[int, int]]:
    """(lowest bit, bits) of near equal parts of a word."""
    sizes = [width // parts + (i < width % parts) for i in range(parts)]
    return [(sum(sizes[:i]), n) for i, n in enumerate(sizes) if n]


def reach(left: int, parts: int) -> list[int]:
    """Radius of each part's ball, -1 for none: of two words within ``left`` bits, some part is within its own.

    If the first left % parts + 1 parts differed by more than left // parts bits, and the
    others by as many at least, there would be more than ``left`` in all.
    """
    return [left // parts if i <= left % parts else left // parts - 1 for i in range(parts)]


def _masks(width: int, parts: int) -> list[tuple]:
    """(width, part, shift, value mask, masks of the bits above and below) of each part."""
    whole = (1 << width) - 1
    return [(width, i, at, _signed((1 << n) - 1), _signed(whole & ~((1 << (at + n)) - 1)), (1 << at) - 1, n) for i, (at, n) in enumerate(segments_of(width, parts))]


def _balls(width: int, parts: int, radius: int) -> list[tuple]:
    """(width, part, left, flip, cost): the points of every part's ball for each radius that can be left."""
    out = []
    for left in range(radius + 1):
        cuts = segments_of(width, parts)
        for i, ((_, n), near) in enumerate(zip(cuts, reach(left, len(cuts)), strict=True)):
            for cost in range(min(near, n) + 1):
                out += [(width, i, left, _signed(sum(1 << b for b in bits)), cost) for bits in combinations(range(n), cost)]
    return out


_VALUE = "(shiftrightunsigned(rest, shift) & ones)"
_OPEN = "(shiftrightunsigned(rest & above, size) | (rest & below))"


def _split(rows: DataFrame, widths: list[int], parts: int, radius: int | None) -> DataFrame:
    """Rows (node, fp, rest, width) by each part of their open bits: the part's value joins the key, the others stay open.

    With a radius they are probes with ``left`` bits to spend, and come once for each point of the part's ball.
    """
    spark = rows.sparkSession
    masks = spark.createDataFrame([m for w in widths for m in _masks(w, parts)], "width int, part int, shift int, ones long, above long, below long, size int")
    cut = rows.join(F.broadcast(masks), "width")
    key, rest = f"xxhash64(node, part, {_VALUE})", f"{_OPEN} as rest, width - size as width"
    if radius is None:
        return cut.selectExpr(f"{key} as node", "fp", rest.split(", width")[0], "width - size as width")
    balls = spark.createDataFrame([b for w in widths for b in _balls(w, parts, radius)], "width int, part int, left int, flip long, cost int")
    key = f"xxhash64(node, part, {_VALUE} ^ flip)"
    return cut.join(F.broadcast(balls), ["width", "part", "left"]).selectExpr(f"{key} as node", "fp", f"{_OPEN} as rest", "width - size as width", "left - cost as left")


def links(fps: DataFrame, radius: int = RADIUS, segments: int = SEGMENTS) -> DataFrame:
    """(one, two): every pair within ``radius`` bits of a table of different fingerprints (fp), checkpointed.

    Each fingerprint is in one table for each segment, under the segment's value. It
    asks for the values in a small Hamming ball around its own: by the pigeonhole
    principle a ball of radius // segments bits, or one bit less in later segments, meets
    every partner in some segment. What a key returns is verified by the complete distance.
    A key with more than ``KEY_ROWS`` fingerprints is split: its open bits, those outside
    the segment, are halves of a word again, to be met within the bits that the ball has
    not spent; and so on until keys are small or no bits are open. So no key pairs more
    than KEY_ROWS rows with a probe, however dense the fingerprints lie, and no
    pair is left out. Null fingerprints have no links.
    """
    if radius < 0 or not 1 <= segments <= BITS:
        raise ValueError("radius must not be negative, segments must be 1 to 64")
    total = fps.count()
    start = few(fps, 8 * total).where("fp is not null").selectExpr("0L as node", "fp", "fp as rest", f"{BITS} as width")
    table, probes = start, start.withColumn("left", F.lit(radius))
    widths, parts, found = [BITS], segments, None
    while widths:
        table, probes = _split(table, widths, parts, None), _split(probes, widths, parts, radius)
        widths = sorted({w - n for w in widths for _, n in segments_of(w, parts)} - {0})
        if found is None:
            table = checkpointed(table)
        counts = table.groupBy("node").agg(F.count("*").alias("n"), F.max("width").alias("w"))
        crowded = checkpointed(few(counts.where((F.col("n") > KEY_ROWS) & (F.col("w") > 0)).select("node"), total))
        n_crowded = crowded.count()
        named = F.broadcast(crowded) if n_crowded <= BROADCAST_ROWS else crowded
        calm = (lambda d: d.join(named, "node", "left_anti")) if n_crowded else (lambda d: d)  # noqa: B023
        met = calm(probes).select("node", F.col("fp").alias("one")).join(calm(table).select("node", F.col("fp").alias("two")), "node")
        near = met.where((F.col("one") < F.col("two")) & (F.bit_count(F.col("one").bitwiseXOR(F.col("two"))) <= radius)).select("one", "two")
        found = near if found is None else found.unionByName(near)
        if not n_crowded:
            break
        table, probes = checkpointed(table.join(named, "node", "left_semi")), checkpointed(probes.join(named, "node", "left_semi"))
        parts = 2
    return checkpointed(few(found.distinct(), 16 * total))


def components(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """(fp, least, root): the least id of each node's component and the node that has it, for nodes with a link; checkpointed.

    ``nodes`` are (fp, least), ``edges`` (one, two) among their fp. Rounds of taking the
    least label among a node and its neighbours, then of the node that the label
    names. A node with many links, and a label that many nodes share, are met by
    joining by weight.
    """
    spark = nodes.sparkSession
    both = checkpointed(edges.unionByName(edges.select(F.col("two").alias("one"), F.col("one").alias("two"))))
    n_both = both.count()
    both = few(both, n_both)
    degrees = both.groupBy(F.col("one").alias("fp")).agg(F.count("*").alias("degree"))
    label = F.struct(F.col("least").isNull().alias("none"), F.col("least"), F.col("fp"))
    state, path = written(few(nodes.join(degrees, "fp").select("fp", "degree", label.alias("label")), n_both))
    total = state.count()
    while total:
        around = join_by_weight(both, state.select(F.col("fp").alias("two"), "label", "degree"), ["two"], "degree", n_both)
        near = around.groupBy(F.col("one").alias("fp")).agg(F.min("label").alias("near"))
        least = F.least("label", F.coalesce("near", "label"))
        lower, middle = written(few(state.join(near, "fp", "left").select("fp", "degree", F.col("label").alias("was"), least.alias("label"), least.getField("fp").alias("root")), total))
        named = lower.groupBy("root").agg(F.count("*").alias("n")).join(lower.select(F.col("fp").alias("root"), F.col("label").alias("up")), "root")
        jumped = join_by_weight(lower, named, ["root"], "n", total).select("fp", "degree", "was", F.least("label", F.coalesce("up", "label")).alias("label"))
        state, fresh_path = written(few(jumped, total))
        discard(spark, path)
        discard(spark, middle)
        path = fresh_path
        if not state.where(F.col("was") != F.col("label")).limit(1).count():
            break
        state = state.drop("was")
    out = checkpointed(state.select("fp", F.col("label.least").alias("least"), F.col("label.fp").alias("root")))
    discard(spark, path)
    return out


def _grouped(rows: DataFrame, radius: int) -> DataFrame:
    """(fp, n, least, root) of the fingerprints whose group has several rows; root is the group's own fingerprint."""
    total = rows.count()
    nodes = checkpointed(few(rows.groupBy("fp").agg(F.min("rid").alias("least"), F.count("*").alias("n")), total))
    found = components(links(nodes.select("fp"), radius), nodes).withColumnRenamed("least", "reached")
    known = nodes.join(found, "fp", "left").where("n > 1 or reached is not null or root is not null")
    return checkpointed(few(known.select("fp", "n", F.coalesce("reached", "least").alias("least"), F.coalesce("root", "fp").alias("root")), total))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = SHINGLE_WORDS, radius: int = RADIUS) -> DataFrame:
    """(rid, fp, tfp, least) of every row: fingerprint and the least id that links of ``radius`` bits reach.

    A null or empty text has fingerprint 0 and is linked like others. Equal
    fingerprints are one node, whatever their number, before any links are sought.
    """
    rows = fingerprints(docs, id_col, text_col, words)
    return join_by_weight(rows, _grouped(rows, radius), ["fp"], "n", rows.count()).select("rid", "fp", "tfp", F.coalesce("least", "rid").alias("least"))


# --- near copies by the similarity of their shingles


def shingle_lists(texts: pa.Array, words: int) -> list[np.ndarray]:
    """Different XXH64 of each text's shingles of ``words`` words, ascending; of a shorter text the whole; of none nothing."""
    out, held = [], []
    for part in parts_of(texts, words):
        hashes, before = part.shingles(words)
        lists = [np.unique(x) for x in np.split(hashes, before[1:-1])]
        held += lists if part.more or held else []
        if not part.more:
            out += [np.unique(np.concatenate([*held, *lists]))] if held else lists
            held = []
    return out


def shingle_hashes(text: str | None, words: int) -> np.ndarray:
    return shingle_lists(pa.array([text], pa.string()), words)[0]


def sketches(hashes: np.ndarray, text: np.ndarray, parts: int = SKETCH_PARTS, least: int = SKETCH_LEAST) -> tuple[np.ndarray, np.ndarray]:
    """(text, key) for each part of the hash space in which a text has shingles: its ``least`` smallest, hashed together.

    Texts that share a part's smallest shingles share its key; with a similarity of s
    that has about the chance s^least for each part. Repeated hashes of a text count once.
    """
    cell = text * parts + (hashes % np.uint64(parts)).astype(np.int64)
    order = np.lexsort((hashes, cell))
    cell, value = cell[order], hashes[order]
    fresh = np.ones(len(cell), bool)
    fresh[1:] = (cell[1:] != cell[:-1]) | (value[1:] != value[:-1])
    cell, value = cell[fresh], value[fresh]
    heads = np.flatnonzero(np.r_[True, cell[1:] != cell[:-1]]) if len(cell) else np.zeros(0, np.int64)
    place = np.arange(len(cell)) - np.repeat(heads, np.diff(np.append(heads, len(cell))))
    value = np.where(place < least, (value + place.astype(np.uint64)) * _ODD, np.uint64(0))
    value ^= value >> np.uint64(29)
    keys = np.add.reduceat(value, heads) * _ODD + (cell[heads] % parts).astype(np.uint64) if len(heads) else value
    return cell[heads] // parts, keys.view(np.int64)


def _prints_and_keys(texts: pa.Array, words: int) -> tuple[np.ndarray, pa.Array]:
    """Fingerprints and sketch keys of each text, read once."""
    fps, sizes, keys, held, kept = np.zeros(len(texts), np.int64), np.zeros(len(texts), np.int64), [], None, []
    for part in parts_of(texts, max(words, SHINGLE_WORDS)):
        held = _added(held, *part.shingles(SHINGLE_WORDS))
        hashes, before = part.shingles(words)
        text = np.repeat(np.arange(part.texts), np.diff(before))
        if part.more or kept:
            kept.append(np.unique(hashes))
        if not part.more:
            fps[part.first : part.first + part.texts] = majority(*held)
            if kept:
                hashes = np.unique(np.concatenate(kept))
                text = np.zeros(len(hashes), np.int64)
            at, key = sketches(hashes, text)
            sizes[part.first : part.first + part.texts] = np.bincount(at, minlength=part.texts)
            keys.append(key)
            held, kept = None, []
    offsets = pa.array(np.concatenate([[0], np.cumsum(sizes)]), pa.int32())
    return fps, pa.ListArray.from_arrays(offsets, pa.array(np.concatenate([*keys, np.zeros(0, np.int64)])))


def shingle_sets(rows: DataFrame, uids: DataFrame, texts: DataFrame, words: int) -> DataFrame:
    """(uid, shingles) of those rows, from a second reading of the texts (rid, tfp, text), which needn't number rows as the first did."""
    wanted = checkpointed(rows.join(uids, "uid", "left_semi").select("uid", F.col("rid").alias("w_rid"), F.col("tfp").alias("w_tfp")))
    n = wanted.count()
    known = F.broadcast(wanted) if n <= BROADCAST_ROWS else wanted

    def run(batches):
        for batch in batches:
            sets = shingle_lists(batch.column(1), words)
            sizes = np.concatenate([[0], np.cumsum([len(x) for x in sets])])
            flat = np.concatenate(sets).view(np.int64) if sets else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(sizes, pa.int32()), pa.array(flat))], names=["uid", "shingles"])

    found = texts.join(known, F.col("rid").eqNullSafe(F.col("w_rid")) & (F.col("tfp") == F.col("w_tfp")))
    return checkpointed(few(found.select("uid", "text").mapInArrow(run, "uid long, shingles array<long>").dropDuplicates(["uid"]), 32 * n))


def _with_degree(pairs: DataFrame) -> DataFrame:
    """(uid, n): in how many pairs (one, two) a row is."""
    return pairs.select(F.col("one").alias("uid")).unionAll(pairs.select("two")).groupBy("uid").agg(F.count("*").alias("n"))


def verified(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The pairs (one, two), checkpointed and distinct, whose sets have that Jaccard similarity or more."""
    total = pairs.count()
    named = sets.join(_with_degree(pairs), "uid").select(F.col("uid").alias("two"), "n", F.col("shingles").alias("b"))
    left = join_by_weight(pairs, named.select(F.col("two").alias("one"), "n", F.col("b").alias("a")), ["one"], "n", total).drop("n")
    full = join_by_weight(checkpointed(few(left, 32 * total)), named, ["two"], "n", total)
    common = F.size(F.array_intersect("a", "b"))
    return full.where(common >= similarity * (F.size("a") + F.size("b") - common)).select("one", "two")


def similar_pairs(rows: DataFrame, texts: DataFrame, words: int, similarity: float) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Links (one, two) of rows (uid, keys) to the ends of their keys; (uid, key) of crowded keys; (uid, shingles).

    Of the rows of a key, each is paired with the first and the last: that is all there
    is to a key of two rows. Keys of more rows are crowded; ``crossing_links`` does the
    rest of them. Similarities are exact, over whole texts, which only rows with a
    partner need.
    """
    keyed, n_keys = rows.select("uid", F.explode("keys").alias("key")), rows.count() * SKETCH_PARTS
    shared = checkpointed(few(keyed.groupBy("key").agg(F.min("uid").alias("first"), F.max("uid").alias("last"), F.count("*").alias("n")).where("n > 1"), n_keys))
    ends = checkpointed(few(join_by_weight(keyed, shared, ["key"], "n", n_keys).where("n is not null"), n_keys))
    both = ends.select("uid", F.explode(F.array("first", "last")).alias("end")).where("uid <> end")
    pairs = checkpointed(few(both.select(F.least("uid", "end").alias("one"), F.greatest("uid", "end").alias("two")).distinct(), n_keys))
    sets = shingle_sets(rows, _with_degree(pairs).select("uid"), texts, words)
    return verified(pairs, sets, similarity), ends.where("n > 2").select("uid", "key"), sets


def _labelled(rows: DataFrame, found: DataFrame, column: str, name: str) -> DataFrame:
    """``rows`` with the label of the row that ``column`` names: the root that it hangs on, else itself."""
    roots = found.where("fp <> root").select(F.col("fp").alias(column), F.col("root").alias("__root"))
    n = rows.groupBy(column).agg(F.count("*").alias("__n"))
    met = join_by_weight(rows, roots.join(n, column), [column], "__n", rows.count())
    return met.withColumn(name, F.coalesce("__root", column)).drop("__root", "__n")


def cell_links(uid: np.ndarray, label: np.ndarray, offsets: np.ndarray, tokens: np.ndarray, similarity: float) -> list[tuple[int, int]]:
    """Links that join rows of different labels wherever a pair of them has the similarity: a forest, not all pairs.

    Each row outside the commonest label is compared with all others at once, by marks
    on its shingles. Labels that have been linked count as one from then on.
    """
    place = np.unique(tokens, return_inverse=True)[1]
    group = np.unique(label, return_inverse=True)[1]
    size, mark, out = np.diff(offsets), np.zeros(int(place.max(initial=-1)) + 1, np.int32), []
    for i in np.flatnonzero(group != np.bincount(group).argmax()).tolist():
        other = group != group[i]
        if not other.any():
            break
        mine = place[offsets[i] : offsets[i + 1]]
        mark[mine] = 1
        common = np.add.reduceat(mark[place], offsets[:-1])
        mark[mine] = 0
        met = np.flatnonzero(other & (common >= similarity * (size + size[i] - common)))
        for j in met.tolist():
            if group[j] != group[i]:
                out.append((int(uid[i]), int(uid[j])))
                group[group == group[j]] = group[i]
    return out


def compared(cells: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """(one, two), checkpointed: the ``cell_links`` of rows (cell, uid, label), of which each cell has a bounded number of shingles."""
    full = cells.join(sets, "uid").select("cell", "uid", "label", "shingles").repartition("cell").sortWithinPartitions("cell", "uid")

    def links_of(held):
        uid, label = (np.concatenate([h[i] for h in held]) for i in (0, 1))
        offsets = np.concatenate([[0], np.cumsum(np.concatenate([h[2] for h in held]))])
        found = cell_links(uid, label, offsets, np.concatenate([h[3] for h in held]), similarity)
        return pa.RecordBatch.from_arrays([pa.array([x[i] for x in found], pa.int64()) for i in (0, 1)], names=["one", "two"])

    def run(batches):
        now, held = None, []
        for batch in batches:
            cell, uid, label = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1, 2))
            sizes, values = batch.column(3).value_lengths().to_numpy(zero_copy_only=False), batch.column(3).flatten().to_numpy(zero_copy_only=False)
            ends = np.concatenate([[0], np.cumsum(sizes)])
            heads = np.flatnonzero(np.r_[True, cell[1:] != cell[:-1]]) if len(cell) else []
            for a, b in zip(heads, [*heads[1:], len(cell)], strict=True):
                if cell[a] != now:
                    if held:
                        yield links_of(held)
                    now, held = cell[a], []
                held.append((uid[a:b], label[a:b], sizes[a:b], values[ends[a] : ends[b]]))
        if held:
            yield links_of(held)

    return checkpointed(few(full.mapInArrow(run, "one long, two long"), 32 * sets.count()))


def _merged(found: DataFrame, fresh_links: DataFrame) -> DataFrame:
    """``found`` (components) with links among its rows: components of the labels, of which few are met, then theirs of the rows."""
    ends = _labelled(checkpointed(few(_labelled(fresh_links, found, "one", "a"), found.count())), found, "two", "b").where("a <> b").select(F.col("a").alias("one"), F.col("b").alias("two"))
    edges = checkpointed(few(ends.distinct(), found.count()))
    if not edges.limit(1).count():
        return found
    met = edges.select(F.col("one").alias("fp")).union(edges.select("two")).distinct()
    labels = found.where("fp = root").select("fp", "least").join(met, "fp", "left_semi")
    moved = components(edges, labels).select(F.col("fp").alias("root"), F.col("least").alias("to_least"), F.col("root").alias("to_root"))
    weights = found.groupBy("root").agg(F.count("*").alias("n"))
    out = join_by_weight(found, moved.join(weights, "root"), ["root"], "n", found.count())
    out = out.select("fp", F.coalesce("to_least", "least").alias("least"), F.coalesce("to_root", "root").alias("root"))
    return checkpointed(few(out, found.count()))


def _split_keys(crowded: DataFrame, found: DataFrame) -> DataFrame:
    """Rows (key, uid, n, label) of the keys whose rows are in several components, checkpointed."""
    n = crowded.count()
    labelled = checkpointed(few(_labelled(crowded, found, "uid", "label"), n))
    split = labelled.groupBy("key").agg(F.count("*").alias("m"), F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo < hi").select("key", "m")
    return checkpointed(few(join_by_weight(labelled, checkpointed(few(split, n)), ["key"], "m", n).where("m is not null").drop("m"), n))


def crossing_links(crowded: DataFrame, sets: DataFrame, found: DataFrame, similarity: float, cell: int) -> DataFrame:
    """``found`` (components) after all pairs among the rows of each crowded key (key, uid) that it leaves apart.

    A key whose rows are one component needs nothing more. The rows of the others are
    dealt into blocks of about ``cell`` shingles, by a hash, and compared block by block,
    which joins nearly all that belong together, in work that is linear in the rows. Of
    keys that still hold several components, the rows outside the largest one meet
    every other block of their key. No pair of a key is left out, none is emitted
    but the links of a forest, and no task holds more than two blocks.
    """
    many = crowded.count()
    sized = checkpointed(few(crowded.join(sets.select("uid", F.size("shingles").alias("n")), "uid"), many))
    blocks = F.ceil(F.col("total") / cell).cast("int")
    turn = F.pmod(F.xxhash64("key", "uid"), F.greatest(blocks, F.lit(1))).cast("int")

    rows = _split_keys(sized, found)
    if not rows.limit(1).count():
        return found
    totals = checkpointed(few(rows.groupBy("key").agg(F.sum("n").alias("total"), F.count("*").alias("m")), many))
    dealt = join_by_weight(rows, totals, ["key"], "m", rows.count())
    found = _merged(found, compared(dealt.select(F.xxhash64("key", turn).alias("cell"), "uid", "label"), sets, similarity))

    rows = _split_keys(rows.drop("label"), found)
    if not rows.limit(1).count():
        return found
    by_label = rows.groupBy("key", "label").agg(F.sum("n").alias("total"), F.count("*").alias("m"))
    best = F.struct("m", "label")
    tops = by_label.groupBy("key").agg(F.max_by("label", best).alias("top"), F.max_by("total", best).alias("inside"), F.sum("total").alias("all"), F.sum("m").alias("m"))
    tops = checkpointed(few(tops, many))
    named = join_by_weight(rows, tops, ["key"], "m", rows.count())
    inside, outside = (F.greatest(F.lit(1), F.ceil(F.col(c) / cell)).cast("int") for c in ("inside", "outside"))
    named = named.withColumn("outside", F.col("all") - F.col("inside")).withColumn("t", inside).withColumn("o", outside).withColumn("is_top", F.col("label") == F.col("top"))
    spread = F.pmod(F.xxhash64("key", "uid"), F.when(F.col("is_top"), F.col("t")).otherwise(F.col("o"))).cast("int")
    placed = named.withColumn("mine", F.when(F.col("is_top"), spread).otherwise(F.col("t") + spread))
    others = placed.withColumn("other", F.explode(F.sequence(F.when(F.col("is_top"), F.col("t")).otherwise(F.lit(0)), F.col("t") + F.col("o") - 1))).where("other <> mine")
    return _merged(found, compared(others.select(F.xxhash64("key", F.least("mine", "other"), F.greatest("mine", "other")).alias("cell"), "uid", "label"), sets, similarity))


def near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = COPY_WORDS, similarity: float = COPY_SIMILARITY, radius: int = RADIUS) -> DataFrame:
    """(rid, tfp, spare) of the rows that go: of each group of near copies the row with the least id stays.

    Rows are linked if their SimHash fingerprints (as in ``near_duplicates``) are within
    ``radius`` bits, or if their shingles of ``words`` words have a Jaccard similarity of
    ``similarity`` or more: 64 bits can't tell 0.8 from less, so such pairs are sought
    by sketch keys and verified exactly. Rows without words (null, empty or blank texts)
    form one group. A null id stays if no row of its group has one; of repeats of one
    row, one stays (the others are ``spare``). An empty table gives no rows.
    """
    plain = docs.select(F.col(id_col).cast("long").alias("rid"), F.monotonically_increasing_id().alias("uid"), F.col(text_col).cast("string").alias("text"), text_fingerprint(text_col).alias("tfp"))

    def run(batches):
        for batch in batches:
            fps, lists = _prints_and_keys(batch.column(2), words)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(3), pa.array(fps), lists], names=["rid", "uid", "tfp", "fp", "keys"])

    rows = checkpointed(plain.mapInArrow(run, "rid long, uid long, tfp long, fp long, keys array<long>"))
    total = rows.count()
    rows = few(rows, 4 * total)
    # equal fingerprints hang on their first row, and so do links between fingerprints
    firsts = checkpointed(few(rows.groupBy("fp").agg(F.min("uid").alias("first"), F.count("*").alias("n")), total))
    hung = join_by_weight(rows.select("uid", "fp"), firsts.where("n > 1"), ["fp"], "n", total).where("uid <> first").select(F.col("uid").alias("one"), F.col("first").alias("two"))
    ends = firsts.select("fp", "first")
    close = links(ends.select("fp"), radius).join(ends.toDF("one", "a"), "one").join(ends.toDF("two", "b"), "two").select(F.col("a").alias("one"), F.col("b").alias("two"))
    alike, crowded, sets = similar_pairs(rows, plain.select("rid", "tfp", "text"), words, similarity)
    nodes = rows.select(F.col("uid").alias("fp"), F.col("rid").alias("least"))
    found = components(checkpointed(hung.unionByName(close).unionByName(alike)), nodes)
    lone = crowded.select(F.col("uid").alias("fp")).distinct().join(found, "fp", "left_anti")
    known = checkpointed(few(found.unionByName(nodes.join(lone, "fp", "left_semi").withColumn("root", F.col("fp"))), total))
    found = crossing_links(crowded, sets, known, similarity, CELL_SHINGLES)
    gone = found.where("fp <> root").select(F.col("fp").alias("uid"), "root")
    winners = gone.select(F.col("root").alias("uid")).distinct().join(rows.select("uid", F.col("rid").alias("w_rid"), F.col("tfp").alias("w_tfp")), "uid").withColumnRenamed("uid", "root")
    named = checkpointed(few(gone.join(rows.select("uid", "rid", "tfp"), "uid"), total))
    sizes = named.groupBy("root").agg(F.count("*").alias("n")).join(winners, "root")
    spare = F.col("rid").eqNullSafe(F.col("w_rid")) & (F.col("tfp") == F.col("w_tfp"))
    return join_by_weight(named, sizes, ["root"], "n", total).select("rid", "tfp", spare.alias("spare"))


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each group of ``near_copies``, with all its columns."""
    return without_rows(docs, near_copies(docs, id_col, text_col), id_col, text_col)


def op9_simhash(spark, sf_dir: str) -> DataFrame:
    """Every document's fingerprint and component; see ``near_duplicates`` for null, empty and repeated rows."""
    found = near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select(F.col("rid").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.col("least").alias("component_id"))
