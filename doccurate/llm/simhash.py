"""SimHash near-duplicates: exact pairs within a Hamming radius by vantage points, components by stars.

Fingerprints are partitioned by their distances to vantage points. On all 64 bits distances between
random fingerprints crowd around 32 and a ball of radius 4 would cross nearly every boundary, so
the vantage points are used in views: the bits fall into blocks, and a view measures distance on some of
them only. If two fingerprints differ in at most r bits, at least ``blocks - r`` of the blocks are equal, so
in the view on those blocks their distance is 0, and by the triangle bound they have the same distance to each
vantage point. A view's shards are these tuples of distances: no ball crosses a boundary, and
every pair within the radius meets in some shard. There are as few views as leave shards of a bounded size. In a shard a vantage-point tree on the full distance finds
the pairs, with boundary overlap of the radius; only a spanning forest of them leaves the task.

Equal fingerprints are one node, so groups of copies cost one row. A shard beyond HOT nodes is
cut again by views on its remaining bits.
"""

from __future__ import annotations

from functools import partial
from itertools import combinations, islice

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from doccurate.llm.common import Scratch, docs_of, fresh, materialise, table
from doccurate.llm.token_store import mix

_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
#: Shingles whose bits are counted at once; nodes of a shard that is cut again; points compared directly.
CHUNK, HOT, DIRECT = 1 << 16, 4096, 256
#: Points of a tree's leaf; nodes that a shard has about, if fingerprints are spread evenly.
LEAF, SHARD = 16, 64


def fingerprint(text: bytes | None, words: int = 4, seed: int = 42) -> int:
    """64-bit SimHash of the word shingles of a text; 0 without words."""
    found = text.translate(_LOWER).split() if text else []
    if not found:
        return 0
    n = max(len(found) - words + 1, 1)
    joined = b" ".join(found)
    ends = np.cumsum([len(w) + 1 for w in found]) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])[:n].tolist()
    ends = ends[min(words, len(found)) - 1 :].tolist()
    digest, total = xxhash.xxh64_intdigest, np.zeros(64, np.int64)
    hashes = (digest(joined[a:b], seed) for a, b in zip(starts, ends, strict=True))
    while len(some := np.fromiter(islice(hashes, CHUNK), np.uint64)):
        total += np.unpackbits(some.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * total > n, bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame, words: int = 4, seed: int = 42) -> DataFrame:
    """doc_id and fp (the 64 bits as a signed long) of every row."""

    def run(batches):
        for b in batches:
            fps = np.array([fingerprint(t.as_py(), words, seed) for t in b.column(1).cast(pa.binary())], np.uint64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view(np.int64))], ["doc_id", "fp"])

    return docs_of(docs).mapInArrow(run, "doc_id long, fp long")


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _blocks(bits: list[int], n: int) -> list[int]:
    return [sum(1 << b for b in part.tolist()) for part in np.array_split(np.array(bits), n)]


def _views(blocks: list[int], radius: int) -> list[int]:
    """Masks of all choices of blocks that a pair within the radius has one of equal."""
    return [sum(c) for c in combinations(blocks, len(blocks) - radius)]


def _path(fp, mask: int, points: int = 12):
    """Distances within the mask to a fixed set of vantage points, five bits each."""
    rng = np.random.default_rng(9)
    parts = [F.bit_count(fp.bitwiseXOR(F.lit(_signed(int(v)))).bitwiseAND(F.lit(_signed(mask)))).cast("long") for v in rng.integers(0, 1 << 64, points, np.uint64)]
    out = parts[0]
    for p in parts[1:]:
        out = F.shiftleft(out, 5).bitwiseOR(p)
    return out


def _sharded(nodes: DataFrame, masks: list[int], *also: str) -> DataFrame:
    """One row a node and view: also columns, view, path, fp."""
    each = F.array(*(F.struct(F.lit(k).alias("view"), _path(F.col("fp"), m).alias("path")) for k, m in enumerate(masks)))
    return nodes.select(*also, "fp", F.inline(each)).select(*also, "view", "path", "fp")


def near(points: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Spanning forest (indexes) of the links within the radius among rows of 64-bit words.

    A vantage-point tree: points go inside or outside of the median distance from the first one, and
    by the triangle bound only those within the radius of that boundary are compared across it.
    """
    root = list(range(len(points)))

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    out = []

    def link(a: np.ndarray, b: np.ndarray) -> None:
        for x, y in zip(a.tolist(), b.tolist(), strict=True):
            if (p := find(x)) != (q := find(y)):
                root[max(p, q)] = min(p, q)
                out.append((x, y))

    def apart(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        total = np.zeros((len(a), len(b)), np.int16)
        for w in range(points.shape[1]):
            total += np.bitwise_count(points[a, w][:, None] ^ points[b, w][None])
        return total

    def across(a: np.ndarray, b: np.ndarray) -> None:
        for k in range(0, len(a), DIRECT):
            i, j = np.nonzero(apart(a[k : k + DIRECT], b) <= radius)
            link(a[k + i], b[j])

    todo = [np.arange(len(points))]
    while todo:
        own = todo.pop()
        if len(own) <= LEAF:
            i, j = np.nonzero(np.triu(apart(own, own) <= radius, 1))
            link(own[i], own[j])
            continue
        distance = apart(own[:1], own)[0]
        middle = int(np.median(distance))
        inside = distance <= middle
        if inside.all():
            inside = distance < middle
        if not inside.any():  # all at one distance of the vantage point
            across(own, own)
            continue
        edge = distance[inside].max()
        todo += [own[inside], own[~inside]]
        across(own[inside & (distance > edge - radius)], own[~inside & (distance <= edge + radius)])
    return out


def _links(shards: DataFrame, keys: list[str], radius: int, words: tuple[str, ...] = ("fp",), node: str = "fp") -> DataFrame:
    """a > b: linked nodes, a spanning forest of each shard (rows with equal keys); words: the columns of a signature."""
    columns = [*keys, *words, *([node] if node not in words else [])]
    first, at = len(keys), columns.index(node)

    def run(batches):
        rest: list[np.ndarray] = [np.zeros(0, np.int64) for _ in columns]

        def edges(rows: list[np.ndarray]):
            points = np.stack(rows[first : first + len(words)], 1).view(np.uint64)
            fresh = np.zeros(len(points), bool)
            fresh[:1] = True
            for c in rows[:first]:
                fresh[1:] |= c[1:] != c[:-1]
            heads = np.concatenate([np.flatnonzero(fresh), [len(points)]])
            sizes, a, b = np.diff(heads), [], []
            two = heads[:-1][sizes == 2]
            two = two[np.bitwise_count(points[two] ^ points[two + 1]).sum(axis=1) <= radius]
            for start, size in zip(heads[:-1][sizes > 2].tolist(), sizes[sizes > 2].tolist(), strict=True):
                for i, j in near(points[start : start + size], radius):
                    a.append(start + i)
                    b.append(start + j)
            a, b = (rows[at][np.concatenate([two + k, x]).astype(int)] for k, x in enumerate((a, b)))
            return pa.RecordBatch.from_arrays([pa.array(np.maximum(a, b)), pa.array(np.minimum(a, b))], ["a", "b"])

        for batch in batches:
            got = [np.concatenate([r, c.to_numpy().astype(np.int64)]) for r, c in zip(rest, batch.columns, strict=True)]
            if not len(got[0]):
                continue
            last = np.logical_and.reduce([c == c[-1] for c in got[:first]])
            cut = int(np.flatnonzero(last)[0])  # the last shard can go on in the next batch
            rest = [c[cut:] for c in got]
            yield edges([c[:cut] for c in got])
        yield edges(rest)

    dealt = shards.select(*columns).repartition(*keys).sortWithinPartitions(*keys, node)
    return dealt.mapInArrow(run, "a long, b long").filter("a > b").distinct()


def blocks_for(count: int, radius: int) -> int:
    """Blocks of the views: the fewest (and so the fewest views) that leave about SHARD of count nodes to a shard."""
    return next(n for n in range(radius + 1, 65) if n == 64 or count >> (64 * (n - radius) // n) <= SHARD)


def links(spark: SparkSession, nodes: DataFrame, radius: int = 4, blocks: int | None = None) -> DataFrame:
    """Pairs (a > b) that connect all distinct fingerprints ``fp`` of nodes within the radius.

    blocks: of the views, by default as the number of nodes asks for. Any number finds the same components.
    """
    every, blocks = (1 << 64) - 1, blocks or blocks_for(nodes.count(), radius)
    masks = _views(_blocks(list(range(64)), blocks), radius)
    shards = materialise(spark, _sharded(nodes.select("fp"), masks), "shards")
    hot = materialise(spark, shards.groupBy("view", "path").count().filter(F.col("count") > HOT).select("view", "path"), "hot")
    if hot.isEmpty():
        return _links(shards, ["view", "path"], radius)
    found = _links(shards.join(hot, ["view", "path"], "left_anti"), ["view", "path"], radius)
    deep = shards.join(hot, ["view", "path"], "left_semi")
    for k, mask in enumerate(masks):
        inner = _views(_blocks([b for b in range(64) if not mask >> b & 1 and every >> b & 1], max(blocks, radius + 2)), radius)
        some = deep.filter(F.col("view") == k).select(F.col("view").alias("outer"), F.col("path").alias("way"), "fp")
        found = found.union(_links(_sharded(some, inner, "outer", "way"), ["outer", "way", "view", "path"], radius))
    return found.distinct()


def components(spark: SparkSession, pairs: DataFrame, most_rounds: int = 60) -> DataFrame:
    """node, root (the least node that it reaches) for every node of pairs(a > b), by large and small stars."""

    def state(df: DataFrame) -> tuple:
        return tuple(df.agg(F.count("*"), F.coalesce(F.bit_xor(F.xxhash64("a", "b")), F.lit(0))).first())

    own, now = Scratch(spark), materialise(spark, pairs.select("a", "b"), "links")
    known = state(now)
    for _ in range(most_rounds):
        own, old = Scratch(spark), own
        both = now.union(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        passing = Scratch(spark)
        least = passing(both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m")), "least")
        large = both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        large = passing(large, "large")
        least = passing(large.groupBy("a").agg(F.min("b").alias("m")), "least")
        small = large.join(least, "a").filter("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).union(least.select("a", F.col("m").alias("b")))
        now = own(small.distinct(), "links")
        passing.drop()
        old.drop()
        before, known = known, state(now)
        if before == known:
            return now.select(F.col("a").alias("node"), F.col("b").alias("root"))
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")


def near_duplicates(spark: SparkSession, docs: DataFrame, words: int = 4, radius: int = 4, seed: int = 42) -> DataFrame:
    """doc_id, fp and component_id (least doc_id that is reached by links of at most ``radius`` bits) of every row.

    Null and empty texts have fingerprint 0 and are linked like others; repeated rows share a component;
    null ids are never a component's id unless it has no other; other columns are ignored.
    """
    own = materialise(spark, fingerprints(docs, words, seed), "fingerprints")
    nodes = materialise(spark, own.groupBy("fp").agg(F.min("doc_id").alias("least")), "nodes")
    roots = components(spark, links(spark, nodes, radius))
    at = nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), "least")
    at = materialise(spark, at, "roots")
    first = materialise(spark, at.groupBy("root").agg(F.min("least").alias("component_id")), "first")
    named = materialise(spark, at.join(first, "root").select("fp", "component_id"), "named")
    return own.join(named, "fp").select("doc_id", "fp", "component_id")


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(spark, table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


#: Least similarity of near copies as a fraction: four fifths.
ALIKE, OF = 4, 5
#: 64-bit words of a parity mark; rows whose grams are counted at least, the share of all rows, the count and number of frequent grams.
MARK, SAMPLE, SHARE, FREQUENT, MOST = 8, 20_000, 16, 3, 500_000
#: Words of 64 bits, one for as many row numbers, that are broadcast at most.
WORDS = 1 << 20
#: Rows that each row of a gram is first compared with on whole sets; bits in which fingerprints of the first links differ at most.
NEAREST, RADIUS = 3, 4


def folded(text: bytes | None) -> list[bytes]:
    return text.translate(_LOWER).split() if text else []


def shingles(found: list[bytes], words: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word shingles; a shorter text is one shingle, one without words has none."""
    if not found:
        return np.zeros(0, np.uint64)
    n = max(len(found) - words + 1, 1)
    joined = b" ".join(found)
    ends = np.cumsum([len(w) + 1 for w in found]) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])[:n].tolist()
    ends = ends[min(words, len(found)) - 1 :].tolist()
    return np.unique(np.fromiter((xxhash.xxh64_intdigest(joined[a:b]) for a, b in zip(starts, ends, strict=True)), np.uint64, n))


def majority(hashes: np.ndarray) -> int:
    """The SimHash of a set of hashes: a bit is 1 where more than half of them have it; 0 of none."""
    total = np.zeros(64, np.int64)
    for k in range(0, len(hashes), CHUNK):
        total += np.unpackbits(hashes[k : k + CHUNK].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * total > len(hashes), bitorder="little").tobytes(), "little")


def alike(a: np.ndarray, b: np.ndarray) -> bool:
    """Whether two sets have a Jaccard similarity of ALIKE / OF at least, in whole numbers."""
    common = len(np.intersect1d(a, b, assume_unique=True))
    return len(a) + len(b) > 0 and common * OF >= (len(a) + len(b) - common) * ALIKE


def _fits(a: np.ndarray, b: np.ndarray, from_a: np.ndarray, from_b: np.ndarray) -> np.ndarray:
    """Which pairs sizes and places leave open: the common grams are the first common one and later ones."""
    return np.minimum(a - from_a, b - from_b) >= -(-ALIKE * (a + b) // (ALIKE + OF))


def _apart(marks_a: np.ndarray, marks_b: np.ndarray) -> np.ndarray:
    """Differing bits of marks, summed word by word (words: the last axis)."""
    return sum(np.bitwise_count(marks_a[..., w] ^ marks_b[..., w]).astype(np.int16) for w in range(MARK))


def _may(a: np.ndarray, b: np.ndarray, from_a: np.ndarray, from_b: np.ndarray, distance: np.ndarray) -> np.ndarray:
    """Which pairs sizes, places and the distance of marks leave open. A pair that is alike is left open where its first common gram is.

    Marks differ in no more bits than the sets in grams.
    """
    return _fits(a, b, from_a, from_b) & (distance <= a + b - 2 * -(-ALIKE * (a + b) // (ALIKE + OF)))


def _blocks_of(rows: np.ndarray, marks: np.ndarray, some: np.ndarray):
    """i, j, distance, open: blocks of the rows ``some`` against all rows (rows: node, size, place, root of one gram).

    Pairs of one root are never open: nothing can come of them.
    """
    _, size, place, root = rows.T
    for k in range(0, len(some), DIRECT):
        i = some[k : k + DIRECT]
        for start in range(0, len(rows), HOT):
            j = np.arange(start, min(start + HOT, len(rows)))
            distance = _apart(marks[i][:, None], marks[j][None])
            yield i, j, distance, _may(size[i][:, None], size[j][None], place[i][:, None], place[j][None], distance) & (root[i][:, None] != root[j][None])


def _opened(rows: np.ndarray, marks: np.ndarray) -> np.ndarray:
    """Rows that some pair of the gram is left open for; a gram of more than HOT rows keeps all."""
    if len(rows) > HOT:
        return np.ones(len(rows), bool)
    keep = np.zeros(len(rows), bool)
    for i, _, _, may in _blocks_of(rows, marks, np.arange(len(rows))):
        keep[i] |= may.any(axis=1)
    return keep


def _nearest(rows: np.ndarray, marks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each row's NEAREST open rows by marks, in a gram of more than HOT rows among HOT of them, evenly drawn."""
    own = np.arange(len(rows))
    hubs = own if len(rows) <= HOT else np.unique(np.linspace(0, len(rows) - 1, HOT).astype(np.int64))
    left, right = [], []
    for j, i, distance, may in _blocks_of(rows, marks, hubs) if len(rows) > HOT else ():
        best = np.where(may, distance, np.iinfo(np.int16).max).argmin(axis=0)  # of this block's hubs
        found = may[best, np.arange(len(i))]
        left.append(i[found])
        right.append(j[best][found])
    for i, j, distance, may in _blocks_of(rows, marks, own) if len(rows) <= HOT else ():
        distance = np.where(may, distance, np.iinfo(np.int16).max)
        best = np.argpartition(distance, min(NEAREST, len(j) - 1) - 1, axis=1)[:, :NEAREST]
        x, y = np.nonzero(np.take_along_axis(may, best, 1))
        left.append(i[x])
        right.append(j[best[x, y]])
    return np.concatenate([*left, np.zeros(0, np.int64)]), np.concatenate([*right, np.zeros(0, np.int64)])


def _across(rows: np.ndarray, marks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All open pairs of different roots: the rows outside of the largest group against all."""
    root = rows[:, 3]
    _, group, times = np.unique(root, return_inverse=True, return_counts=True)
    left, right = [], []
    for i, j, _, may in _blocks_of(rows, marks, np.flatnonzero(group != times.argmax())):
        x, y = np.nonzero(may)
        left.append(i[x])
        right.append(j[y])
    return np.concatenate([*left, np.zeros(0, np.int64)]), np.concatenate([*right, np.zeros(0, np.int64)])


def _buckets(shards: DataFrame, work, ddl: str) -> DataFrame:
    """work(columns, heads) for the rows of whole grams (columns: gram, node, ...; heads: first row of each gram, and the end)."""

    def run(batches):
        rest = None
        for batch in batches:
            if not batch.num_rows:
                continue
            batch = pa.Table.from_batches([batch])
            rest = batch if rest is None else pa.concat_tables([rest, batch])
            gram = rest.column(0).to_numpy()
            cut = int(np.searchsorted(gram, gram[-1]))  # the last gram can go on in the next batch
            if cut:
                yield from work(rest.slice(0, cut).combine_chunks(), gram[:cut])
                rest = rest.slice(cut)
        if rest is not None:
            yield from work(rest.combine_chunks(), rest.column(0).to_numpy())

    return shards.select("gram", *(c for c in shards.columns if c != "gram")).repartition("gram").sortWithinPartitions("gram", "node").mapInArrow(run, ddl)


def _heads(gram: np.ndarray) -> np.ndarray:
    return np.concatenate([[0], np.flatnonzero(gram[1:] != gram[:-1]) + 1, [len(gram)]])


def _numbers(part: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Rows (node, size, place, root) and marks of a part of shards."""
    rows = np.stack([part.column(c).to_numpy().astype(np.int64) for c in ("node", "size", "place", "root")], 1)
    return rows, np.frombuffer(b"".join(part.column("mark").to_pylist()), np.uint64).reshape(-1, MARK)


def _pairs_of_two(rows: np.ndarray, marks: np.ndarray, heads: np.ndarray) -> np.ndarray:
    """First rows of the grams of two rows that are left open, all at once: most grams have two."""
    two = heads[:-1][np.diff(heads) == 2]
    (_, a, from_a, p), (_, b, from_b, q) = rows[two].T, rows[two + 1].T
    return two[_may(a, b, from_a, from_b, _apart(marks[two], marks[two + 1])) & (p != q)]


def _proposed(shards: DataFrame, chosen) -> DataFrame:
    """a > b: pairs of different roots among chosen(rows, marks) of each gram of shards(gram, node, size, place, root, mark)."""

    def work(part, gram):
        rows, marks = _numbers(part)
        heads = _heads(gram)
        two = _pairs_of_two(rows, marks, heads)
        left, right = [two], [two + 1]
        for start, end in zip(heads[:-1].tolist(), heads[1:].tolist(), strict=True):
            if end - start > 2 and (rows[start:end, 3] != rows[start, 3]).any():
                i, j = chosen(rows[start:end], marks[start:end])
                left.append(start + i)
                right.append(start + j)
        i, j = np.concatenate(left), np.concatenate(right)
        apart = rows[i, 3] != rows[j, 3]
        pairs = np.unique(np.sort(np.stack([rows[i[apart], 0], rows[j[apart], 0]], 1), axis=1), axis=0)
        yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 1]), pa.array(pairs[:, 0])], ["a", "b"])

    return _buckets(shards, work, "a long, b long").filter("a > b").distinct()


def among(rows: DataFrame, number: str, some: DataFrame, keep) -> DataFrame:
    """The rows whose number is some's only column. Numbers are dense (from 0 in each partition that gave them), so the wanted ones
    are sent as a bit a row: rows of long texts are not dealt out. More than WORDS words of bits are joined by number instead.

    keep(df, name) writes a table that stays as long as the result is read.
    """
    at, bits = fresh(rows.columns, "_at", "_bits")
    (own,) = some.columns
    words = some.groupBy(F.shiftright(own, 6).alias(at)).agg(F.bit_or(F.expr(f"shiftleft(1L, cast(`{own}` & 63L as int))")).alias(bits))
    words = keep(words, "bits")
    if words.count() > WORDS:
        return rows.join(some.select(F.col(own).alias(number)).distinct(), number, "left_semi")
    told = rows.join(F.broadcast(words), F.shiftright(number, 6) == F.col(at))
    return told.filter(F.expr(f"shiftright(`{bits}`, cast(`{number}` & 63L as int)) & 1L = 1L")).select(*rows.columns)


def _confirmed(pairs: DataFrame, texts: DataFrame, words: int, keep: Scratch) -> DataFrame:
    """The pairs whose shingle sets are alike; texts: node, text. Only the texts of some pair are moved."""

    def run(batches):
        own: dict[bytes, np.ndarray] = {}

        def set_of(text: bytes) -> np.ndarray:
            if len(own) >= 256:
                own.clear()
            if text not in own:
                own[text] = shingles(folded(text), words)
            return own[text]

        for b in batches:
            x, y = (b.column(k).cast(pa.binary()).to_pylist() for k in (2, 3))
            told = pa.array([alike(set_of(p), set_of(q)) for p, q in zip(x, y, strict=True)], pa.bool_())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], ["a", "b"]).filter(told)

    with_a = pairs.join(among(texts, "node", pairs.select("a"), keep).select(F.col("node").alias("a"), F.col("text").alias("x")), "a")
    both = with_a.join(among(texts, "node", pairs.select("b"), keep).select(F.col("node").alias("b"), F.col("text").alias("y")), "b")
    return both.select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


def by_fingerprints(spark: SparkSession, signed: DataFrame, texts: DataFrame, words: int, keep: Scratch) -> DataFrame:
    """a > b: links of signed(node, fp) that fingerprints propose and whole sets confirm.

    Nodes of one fingerprint are proposed with the least of them, and these along the forest that the vantage points give within RADIUS.
    """
    least = keep(signed.groupBy("fp").agg(F.min("node").alias("least")), "least")
    forest = links(spark, least, RADIUS)
    same = signed.join(least, "fp").filter("node > least").select(F.col("node").alias("a"), F.col("least").alias("b"))
    ends = [least.select(F.col("fp").alias(c), F.col("least").alias(n)) for c, n in (("a", "x"), ("b", "y"))]
    other = forest.join(ends[0], "a").join(ends[1], "b").select(F.greatest("x", "y").alias("a"), F.least("x", "y").alias("b"))
    return keep(_confirmed(keep(same.union(other), "proposed"), texts, words, keep), "linked")


def near_links(spark: SparkSession, texts: DataFrame, count: int, words: int = 5, pool: DataFrame | None = None) -> DataFrame:
    """a > b: links of texts(node, text), distinct nodes, that connect whatever pairs of Jaccard >= ALIKE / OF connect, and such pairs only.

    pool has the same texts and maybe others; rows to confirm are looked up there (texts by default).

    SimHashes of the sets, within RADIUS by vantage points, propose the first links. What they miss is found exactly: in one order of all grams, two sets that are alike share one of their first grams (prefixes). Any order
    does; one by frequency in a sample keeps what many texts share out of the prefixes. Each row's nearest rows of other groups in its
    gram's bucket are confirmed on whole sets; then all pairs of a bucket whose groups are still apart. So a group of many near
    copies costs a few confirmations a copy, and no pair that could join two groups is left out.
    """
    share, early, keep = min(1.0, max(SAMPLE / max(count, 1), 1 / SHARE)), Scratch(spark), Scratch(spark)
    pool = texts if pool is None else pool

    def grams(batches):
        for b in batches:
            found = [shingles(folded(t), words) for t in b.column(0).cast(pa.binary()).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([np.zeros(0, np.uint64), *found]).view(np.int64))], ["gram"])

    some = texts.filter(F.pmod(F.xxhash64("node"), F.lit(1 << 20)) < int(share * (1 << 20))).select("text")
    often = some.mapInArrow(grams, "gram long").groupBy("gram").count().filter(F.col("count") >= FREQUENT).orderBy(F.desc("count"), "gram").limit(MOST).toPandas()
    order = np.argsort(often["gram"].to_numpy(np.int64).view(np.uint64))
    sent = spark.sparkContext.broadcast((often["gram"].to_numpy(np.int64).view(np.uint64)[order], often["count"].to_numpy(np.int64)[order]))

    def prefixes(batches):
        frequent, times = sent.value
        for b in batches:
            sizes, firsts, marks, fps = [], [], [], []
            for t in b.column(1).cast(pa.binary()).to_pylist():
                own = shingles(folded(t), words)
                rank = np.zeros(len(own), np.int64)
                if len(frequent) and len(own):
                    at = np.minimum(np.searchsorted(frequent, own), len(frequent) - 1)
                    rank = np.where(frequent[at] == own, times[at], 0)
                length = len(own) - -(-ALIKE * len(own) // OF) + 1 if len(own) else 0
                sizes.append(len(own))
                firsts.append(own[np.lexsort((own, rank))][:length].view(np.int64))
                odd = np.bincount((mix(own, 3) >> np.uint64(32)).astype(np.int64) % (64 * MARK), minlength=64 * MARK) & 1
                marks.append(np.packbits(odd.astype(bool)).tobytes())
                fps.append(majority(own))
            ends = np.cumsum([0, *map(len, firsts)]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([np.zeros(0, np.int64), *firsts])))
            fps = pa.array(np.array(fps, np.uint64).view(np.int64))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sizes, pa.int32()), lists, pa.array(marks, pa.binary()), fps], ["node", "size", "first", "mark", "fp"])

    own = early(texts.select("node", "text").mapInArrow(prefixes, "node long, size int, first array<long>, mark binary, fp long"), "prefixes")
    keep.sweep()
    linked = by_fingerprints(spark, own.select("node", "fp"), pool, words, keep)
    keep.sweep()
    groups = keep(components(spark, linked), "groups")

    def shared(part, gram):
        """Rows of grams that several nodes have, unless there are two and sizes or places rule them out."""
        heads = _heads(gram)
        sizes = np.diff(heads)
        keep = np.repeat(sizes > 1, sizes)
        two = heads[:-1][sizes == 2]
        size, place = part.column("size").to_numpy().astype(np.int64), part.column("place").to_numpy().astype(np.int64)
        closed = two[~_fits(size[two], size[two + 1], place[two], place[two + 1])]
        keep[closed] = keep[closed + 1] = False
        yield from part.filter(pa.array(keep)).to_batches()

    def opened(part, gram):
        rows, marks = _numbers(part)
        heads, keep = _heads(gram), np.zeros(len(gram), bool)
        two = _pairs_of_two(rows, marks, heads)
        keep[two] = keep[two + 1] = True
        for start, end in zip(heads[:-1].tolist(), heads[1:].tolist(), strict=True):
            if end - start > 2:
                keep[start:end] = _opened(rows[start:end], marks[start:end])
        yield from part.filter(pa.array(keep)).to_batches()

    spread = own.select("node", "size", F.posexplode("first").alias("place", "gram")).select("gram", "node", "size", "place")
    spread = early(_buckets(spread, shared, "gram long, node long, size int, place int"), "shared")
    keep.sweep()
    known = own.select("node", "mark").join(groups, "node", "left").withColumn("root", F.coalesce("root", "node"))
    marked = spread.join(known, "node").select("gram", "node", "size", "place", "root", "mark")
    spread = keep(_buckets(marked, opened, "gram long, node long, size int, place int, root long, mark binary"), "open")
    early.drop()
    keep.sweep()
    near = keep(linked.union(_confirmed(keep(_proposed(spread, _nearest), "nearest"), pool, words, keep)), "near")
    keep.sweep()
    roots = components(spark, near)
    apart = spread.drop("root").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    rest = keep(_proposed(apart, _across), "across")
    found = materialise(spark, near.union(_confirmed(rest, pool, words, keep)), "found")
    keep.drop()
    keep.sweep()
    sent.unpersist()
    return found


def one_of_each(spark: SparkSession, docs: DataFrame, words: int = 5) -> DataFrame:
    """docs without near copies: of each group of texts linked by a similarity of 0.8 or more, the row of least doc_id.

    SimHash fingerprints by vantage points propose links, a prefix join finds what they miss. Links are exact Jaccard similarities
    of sets of word shingles (as 64-bit hashes), and none is missed. Null and
    empty texts are one group; of repeated rows one stays, rows with a null id yield to others; a table without rows
    stays so; other columns are kept, whatever their names.
    """
    from pyspark.sql.types import LongType, StructType

    names, where = docs.columns, docs.columns.index("text")
    node, row = fresh(names, "_node", "_row")

    def sign(batches):
        for b in batches:
            found = [xxhash.xxh64_intdigest(b" ".join(folded(t))) for t in b.column(where).cast(pa.binary()).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(np.array(found, np.uint64).view(np.int64))], [*names, node])

    signed = docs.mapInArrow(sign, StructType([*docs.schema.fields]).add(node, LongType()))
    rows, keep = materialise(spark, signed.withColumn(row, F.monotonically_increasing_id()), "signed"), Scratch(spark)
    order = F.struct(F.col("doc_id").isNull().alias("lost"), F.col("doc_id").alias("id"), F.col(row).alias("at"))
    nodes = keep(rows.groupBy(node).agg(F.min(order).alias("first")).select(F.col("first.at").alias("node"), "first"), "nodes")
    pool = rows.select(F.col(row).alias("node"), F.col("text").cast("string").alias("text"))
    texts = among(pool, "node", nodes.select("node"), keep)  # a distinct text by its first row
    roots = components(spark, near_links(spark, texts, nodes.count(), words, pool))
    kept = nodes.join(roots, "node", "left").groupBy(F.coalesce("root", "node").alias("root")).agg(F.min("first").alias("first"))
    kept = materialise(spark, kept.select(F.col("first.at").alias(row)), "kept")
    keep.drop()
    return among(rows, row, kept, partial(materialise, spark)).select(*names)
