"""Near-duplicate documents: one-permutation MinHash, banded buckets, star-shaped candidate edges.

Documents whose 5-word shingle sets have a resemblance of at least 0.75 are
linked, and a component keeps its smallest doc_id.

1. One pass in Arrow batches turns each text into the 128-bit name of its
   shingle set, the set's size and 32 band hashes.  Equal sets collapse to a
   *class* at once, so a group of exact copies costs one row from there on.
2. A bucket is one value of one band.  Its most central class (the one that
   meets most others over all its buckets) is the centre of a star; only
   centre-member pairs are kept, so a bucket of m classes gives m - 1 rows.
3. The full sets of the classes in stars are computed once.  The classes of a
   star meet in blocks of about ``BLOCK``, each with the centre, and a block
   links all its members exactly on the full sets (intersections of a block are
   one matrix product), so a star of one block misses nothing.
4. Stars of several blocks that still hold classes of different components get
   further rounds: ``DRAWS`` members of the largest component and two of any,
   drawn by hash anew, are centres for the classes outside that component.
   Rounds end when one adds no link; they only make the last step small.
5. Stars that still hold several components are compared in full: every class
   outside the largest component meets every class of another component whose
   size allows the threshold, in tasks of two parts of about ``BLOCK`` classes.

At the threshold two sets share none of the 32 bands with a probability of
5e-6.  Nothing is capped or sampled: all pairs that share a bucket are joined or
compared.  Pairs are linear in members but for step 5, whose work is the classes
outside a star's largest component times the classes of the star.

Edge cases: a null or empty text has the empty set and is linked with nothing
(its own component); a null doc_id takes part but is never a component's id
unless the component has no other, then component_id is null and kept is false;
repeated rows of one doc_id each give a row with the same component; an empty
table gives an empty result; columns other than doc_id and text are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from litspark.llm.common import BROADCAST_ROWS, Scratch, drop_rows, small, text_batches
from litspark.llm.components import connected_components
from litspark.llm.oph import band_hashes, signatures
from litspark.llm.words import overlap, set_digest, shingle_set

WIDTH = 5
SIMILARITY = 75
#: Classes of one star that one task compares among themselves.
BLOCK = 256
COLUMNS = 4096
#: Members of a star's largest component that one further round compares with the classes outside it.
DRAWS = 8
BATCH = 256
LAST = 2**63 - 1


def _profiles(rows: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    for batch in rows:
        for at in range(0, batch.num_rows, BATCH):
            part = batch.slice(at, BATCH)
            sets = [shingle_set(t, width) for t in part.column("text").to_pylist()]
            bands = band_hashes(signatures(sets)).view(np.int64)
            full = [len(s) > 0 for s in sets]
            yield pa.RecordBatch.from_arrays(
                [
                    part.column("doc_id"),
                    part.column("tag"),
                    pa.array([len(s) for s in sets], pa.int64()),
                    pa.array([set_digest(s) if ok else None for s, ok in zip(sets, full)], pa.binary()),
                    pa.array([b.tolist() if ok else None for b, ok in zip(bands, full)], pa.list_(pa.int64())),
                ],
                ["doc_id", "tag", "n_shingles", "key", "bands"],
            )


def _sets(rows: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    for batch in rows:
        for at in range(0, batch.num_rows, BATCH):
            sets = [shingle_set(t, width) for t in batch.slice(at, BATCH).column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [pa.array([set_digest(s) for s in sets], pa.binary()), pa.array([s.tobytes() for s in sets], pa.binary())], ["key", "members"]
            )


def _verified(rows: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    """Links of pairs (a, b, a_set, b_set)."""
    for batch in rows:
        keep = []
        for a, b in zip(batch.column("a_set").to_pylist(), batch.column("b_set").to_pylist()):
            x, y = np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)
            both = overlap(x, y)
            keep.append(100 * both >= percent * (len(x) + len(y) - both))
        yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], ["a", "b"]).filter(pa.array(keep, pa.bool_()))


def shared_counts(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of the intersections of all pairs of a bounded list of sets."""
    values, inverse, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    places = np.cumsum(counts > 1) - 1
    owner = np.repeat(np.arange(len(sets)), [len(x) for x in sets])
    common = counts[inverse] > 1
    column, row = places[inverse[common]], owner[common]
    out = np.zeros((len(sets), len(sets)), np.float32)
    order = np.argsort(column, kind="stable")
    column, row = column[order], row[order]
    for at in range(0, int(column[-1]) + 1 if len(column) else 0, COLUMNS):
        low, high = np.searchsorted(column, (at, at + COLUMNS))
        part = np.zeros((len(sets), COLUMNS), np.float32)
        part[row[low:high], column[low:high] - at] = 1
        out += part @ part.T
    return out.astype(np.int64)


def spanning_links(sets: list[np.ndarray], percent: int, labels: list | None = None) -> list[tuple[int, int]]:
    """Links that join all members of a block that are linked at all; pairs already joined, by equal labels too, are passed over."""
    first: dict = {}
    above = [first.setdefault(c, i) for i, c in enumerate(labels)] if labels else list(range(len(sets)))
    sizes = [len(x) for x in sets]
    counts = shared_counts(sets) if len(sets) > 12 else None

    def root(x: int) -> int:
        while above[x] != x:
            above[x] = x = above[above[x]]
        return x

    out = []
    for i in range(len(sets)):
        if counts is None:
            near = range(i + 1, len(sets))
        else:
            total = np.array(sizes) + sizes[i]
            near = np.flatnonzero(100 * counts[i] >= percent * (total - counts[i])).tolist()
        for j in near:
            x, y = root(i), root(j)
            if x == y or 100 * min(sizes[i], sizes[j]) < percent * max(sizes[i], sizes[j]):
                continue
            if counts is None:
                both = overlap(sets[i], sets[j])
                if 100 * both < percent * (sizes[i] + sizes[j] - both):
                    continue
            above[max(x, y)] = min(x, y)
            out.append((i, j))
    return out


def _blocks(rows: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    """Links inside each block (centre, part) of rows sorted by block."""
    held: dict[bytes, np.ndarray] = {}
    now = None

    def links() -> pa.RecordBatch:
        names = list(held)
        found = spanning_links(list(held.values()), percent) if len(names) > 1 else []
        return pa.RecordBatch.from_arrays([pa.array([names[i] for i, _ in found], pa.binary()), pa.array([names[j] for _, j in found], pa.binary())], ["a", "b"])

    for batch in rows:
        for centre, part, node, members in zip(*(batch.column(c).to_pylist() for c in ("centre", "part", "node", "members"))):
            if (centre, part) != now:
                if held:
                    yield links()
                now, held = (centre, part), {}
            held[node] = np.frombuffer(members, np.uint64)
    if held:
        yield links()


def _crossed(rows: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    """Links between components inside each task (star, low, high) of rows sorted by task."""
    names, sets, labels, now = [], [], [], None

    def links() -> pa.RecordBatch:
        found = spanning_links(sets, percent, labels) if len(set(labels)) > 1 else []
        return pa.RecordBatch.from_arrays([pa.array([names[i] for i, _ in found], pa.binary()), pa.array([names[j] for _, j in found], pa.binary())], ["a", "b"])

    for batch in rows:
        for star, low, high, node, component, members in zip(*(batch.column(c).to_pylist() for c in ("star", "low", "high", "node", "component", "members"))):
            if (star, low, high) != now:
                if names:
                    yield links()
                names, sets, labels, now = [], [], [], (star, low, high)
            names.append(node)
            sets.append(np.frombuffer(members, np.uint64))
            labels.append(component)
    if names:
        yield links()


def _tasks(named: DataFrame, percent: int, block: int) -> DataFrame:
    """(star, low, high, node, component): both sides of every comparison that can still join components of a star.

    ``named(star, node, n, component)``.  Classes of the largest component of a
    star and the others go apart into parts of about ``block``, by logarithm of
    their size so that only neighbouring sizes can be similar; parts of the
    largest component do not meet each other.
    """
    kinds = named.groupBy("star", "component").agg(F.count("*").alias("here"))
    most = kinds.groupBy("star").agg(F.count("*").alias("kinds"), F.max_by("component", F.struct("here", "component")).alias("most")).where("kinds > 1")
    # a hair wider than the exact ratio, so that rounding cannot part sizes that may be similar
    scale = F.floor(F.log(F.col("n").cast("double")) / F.lit(np.log(100 / percent) * (1 + 1e-9))).cast("long") if 0 < percent < 100 else F.lit(0).cast("long")
    own = named.join(small(most), "star").select("star", "node", "component", scale.alias("scale"), (F.col("component") == F.col("most")).alias("main"))
    sized = own.groupBy("star", "scale").agg(F.ceil(F.count(F.when(~F.col("main"), 1)) / block).alias("others"), F.ceil(F.count(F.when(F.col("main"), 1)) / block).alias("mains"))
    facing = sized.select("star", F.explode(F.array(*[F.col("scale") + d for d in (-1, 0, 1)])).alias("scale"), F.col("scale").alias("scale2"), F.col("others").alias("others2"), F.col("mains").alias("mains2"))
    placed = own.join(small(sized), ["star", "scale"]).withColumn("place", F.pmod(F.xxhash64("node"), F.when(F.col("main"), F.col("mains")).otherwise(F.col("others"))))
    met = placed.drop("others", "mains").join(small(facing), ["star", "scale"])
    part = lambda scale, main, place: F.struct(scale.alias("scale"), main.alias("main"), place.alias("place"))
    run = lambda count, main: F.when(count > 0, F.transform(F.sequence(F.lit(0).cast("long"), count - 1), lambda q: part(F.col("scale2"), F.lit(main), q)))
    none = F.array().cast("array<struct<scale:bigint,main:boolean,place:bigint>>")
    others, mains = F.coalesce(run(F.col("others2"), False), none), F.when(~F.col("main"), F.coalesce(run(F.col("mains2"), True), none)).otherwise(none)
    both = met.withColumn("own", part(F.col("scale"), F.col("main"), F.col("place"))).withColumn("other", F.explode(F.concat(others, mains)))
    return both.select("star", F.least("own", "other").alias("low"), F.greatest("own", "other").alias("high"), "node", "component")


def labelled(docs: DataFrame, width: int = WIDTH, percent: int = SIMILARITY, block: int = BLOCK) -> DataFrame:
    """One row per row of ``docs(doc_id, text)``: doc_id, tag, n_shingles, node (its class) and component, both null for an empty set."""
    text_batches(docs.sparkSession)
    scratch = Scratch(docs.sparkSession, "near")
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("tag", F.xxhash64("text"))
    schema = "doc_id long, tag long, n_shingles long, key binary, bands array<long>"
    profiles = scratch.write(source.mapInArrow(lambda rows: _profiles(rows, width), schema))
    first = profiles.where("key is not null").groupBy("key").agg(F.min("doc_id").alias("rep"), F.first("n_shingles").alias("n"), F.first("bands").alias("bands"))
    # a node's name starts with its doc_id in sortable form, so the smallest node of a component is that of its smallest doc_id
    classes = scratch.write(first.select(_node(F.coalesce("rep", F.lit(LAST)), F.col("key")).alias("node"), "key", "n", "bands"), "classes")
    spots = classes.select("node", "n", F.posexplode("bands").alias("band", "value"))
    shared = spots.groupBy("band", "value").agg(F.count("*").alias("size")).where("size > 1")
    members = scratch.write(spots.join(shared, ["band", "value"]))
    met = members.groupBy("node").agg(F.sum("size").alias("met"))
    central = members.join(met, "node").groupBy("band", "value").agg(F.max_by("node", F.struct("met", "node")).alias("centre"))
    placed = scratch.write(members.join(central, ["band", "value"]), "placed")
    stars = scratch.write(placed.select("centre", "node", "n").distinct())

    ids = scratch.write(placed.select(_rep(F.col("node")).alias("pick")).distinct())
    texts = source.withColumn("pick", F.coalesce("doc_id", F.lit(LAST))).join(small(ids), "pick", "left_semi").select("text")
    sets = scratch.write(texts.mapInArrow(lambda rows: _sets(rows, width), "key binary, members binary").dropDuplicates(["key"]), "sets")

    parts = scratch.write(stars.where("node <> centre").groupBy("centre").agg(F.ceil(F.count("*") / block).cast("int").alias("parts")))
    shares = stars.where("node <> centre").select("centre", "node").join(small(parts), "centre").withColumn("part", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int")).drop("parts")
    every = shares.unionByName(shares.select("centre", F.col("centre").alias("node"), "part").distinct()).withColumn("key", _key(F.col("node")))
    laid = every.join(sets, "key").select("centre", "part", "node", "members").repartition("centre", "part").sortWithinPartitions("centre", "part", "node")
    links = scratch.write(laid.mapInArrow(lambda rows: _blocks(rows, percent), "a binary, b binary"), "links")
    labels = connected_components(links, scratch)

    def verify(pairs: DataFrame) -> DataFrame:
        """Pairs that hold on the full sets; the members' sets stay where they are while the pairs are few enough."""
        of_node = sets.join(small(pairs.withColumn("key", _key(F.col("node")))), "key").select("centre", F.col("node").alias("b"), F.col("members").alias("b_set"))
        centre = sets.join(small(pairs.select("centre", _key(F.col("centre")).alias("key")).distinct()), "key")
        both = of_node.join(centre.select("centre", F.col("members").alias("a_set")), "centre")
        return scratch.write(both.select(F.col("centre").alias("a"), "b", "a_set", "b_set").mapInArrow(lambda rows: _verified(rows, percent), "a binary, b binary"), "links")

    split = parts.where("parts > 1").select("centre")
    if not split.isEmpty():
        wide = scratch.write(stars.join(small(split), "centre", "left_semi").select(F.col("centre").alias("star"), "node", "n"))
        turn = 0
        while True:
            turn += 1
            named = wide.join(small(labels), "node", "left").withColumn("component", F.coalesce("component", "node"))
            draws = [F.min(F.struct(F.xxhash64("node", "star", F.lit(turn * 1000 + i)).alias("h"), F.col("node").alias("centre"), F.col("n").alias("centre_n"))).alias(f"c{i}") for i in range(DRAWS)]
            held = named.groupBy("star", "component").agg(F.count("*").alias("here"), *draws)
            largest = F.max_by(F.struct("component", *[f"c{i}" for i in range(DRAWS)]), F.struct("here", "component"))
            others = [F.min(F.struct(F.xxhash64("component", F.lit(turn * 1000 + i)).alias("r"), F.col(f"c{i}").alias("c"))).alias(f"any{i}") for i in range(2)]
            mixed = held.groupBy("star").agg(F.count("*").alias("kinds"), largest.alias("most"), *others).where("kinds > 1")
            rest = named.join(small(scratch.write(mixed, "mixed")), "star").where("component <> most.component")
            chosen = F.array(*[F.col(f"most.c{i}") for i in range(DRAWS)], *[F.col(f"any{i}.c") for i in range(2)])
            pairs = rest.select("node", "n", F.explode(chosen).alias("c")).select("node", "n", "c.centre", "c.centre_n")
            fits = f"node <> centre and 100 * least(n, centre_n) >= {percent} * greatest(n, centre_n)"
            more = verify(scratch.write(pairs.where(fits).select("centre", "node").distinct(), "pairs"))
            if more.isEmpty():
                break
            links = links.unionByName(more)
            labels = connected_components(links, scratch)
        named = wide.join(small(labels), "node", "left").withColumn("component", F.coalesce("component", "node"))
        tasks = scratch.write(_tasks(named, percent, block), "tasks")
        if not tasks.isEmpty():
            whole = tasks.withColumn("key", _key(F.col("node"))).join(sets, "key").withColumns({c: F.to_json(c) for c in ("low", "high")})
            whole = whole.select("star", "low", "high", "node", "component", "members").repartition("star", "low", "high").sortWithinPartitions("star", "low", "high")
            links = links.unionByName(scratch.write(whole.mapInArrow(lambda rows: _crossed(rows, percent), "a binary, b binary"), "links"))
            labels = connected_components(links, scratch)
    return profiles.select("doc_id", "tag", "n_shingles", "key").join(classes.select("key", "node"), "key", "left").join(small(labels), "node", "left").withColumn("component", F.coalesce("component", "node"))


def near_duplicates(docs: DataFrame, width: int = WIDTH, percent: int = SIMILARITY, block: int = BLOCK) -> DataFrame:
    """One row per row of ``docs(doc_id, text)``: doc_id, n_shingles, component_id, kept, and tag, the hash of the text."""
    out = labelled(docs, width, percent, block)
    found = _rep(F.col("component"))
    whose = F.when(F.col("component").isNull(), F.col("doc_id")).when(found < LAST, found)
    return out.select("doc_id", "tag", "n_shingles", whose.alias("component_id"), F.coalesce(F.col("doc_id") == whose, F.lit(False)).alias("kept"))


def _node(rep: Column, key: Column) -> Column:
    """24 bytes: the doc_id so that bytes sort as numbers do, and the name of the set."""
    return F.concat(F.unhex(F.lpad(F.hex(rep.bitwiseXOR(F.lit(-(2**63)))), 16, "0")), key)


def _rep(node: Column) -> Column:
    return F.conv(F.hex(F.substring(node, 1, 8)), 16, -10).cast("long").bitwiseXOR(F.lit(-(2**63)))


def _key(node: Column) -> Column:
    return F.substring(node, 9, 16)


def keep_one(docs: DataFrame) -> DataFrame:
    """``docs`` with one row of each group of near-duplicates: its smallest (doc_id, tag), a null doc_id being the largest.

    Rows with the empty set stay, each being its own group.
    """
    judged = Scratch(docs.sparkSession, "kept").write(labelled(docs).where("component is not null").select("doc_id", "tag", "component"), "judged")
    order = F.struct(F.coalesce("doc_id", F.lit(LAST)).alias("pick"), "tag")
    # the smallest doc_id stands in the component's name, so only rows with it compete
    first = judged.where(F.coalesce("doc_id", F.lit(LAST)) == _rep(F.col("component"))).groupBy("component").agg(F.min(order).alias("first"))
    stays = F.broadcast(first) if first.count() <= BROADCAST_ROWS else first
    gone = judged.join(stays, "component").where(order != F.col("first"))
    kept = drop_rows(docs, gone.select("doc_id", "tag"))
    # rows that repeat the one that stays, doc_id and text
    again = judged.join(stays, "component").where(order == F.col("first")).groupBy("doc_id", "tag").count().where("count > 1").select("doc_id", "tag")
    if again.isEmpty():
        return kept
    once = drop_rows(kept, again)
    return once.unionByName(kept.exceptAll(once).dropDuplicates(["doc_id", "text"]))


#: DuckDB SQL of the query's result on ``documents``, by comparing all documents that share a shingle.
ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[i : i + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 2))) AS i FROM w WHERE len(w) > 0)),
n AS (SELECT w.doc_id, count(g) AS n FROM w LEFT JOIN s USING (doc_id) GROUP BY w.doc_id),
e AS (SELECT a, b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY ALL) JOIN n p ON p.doc_id = a JOIN n q ON q.doc_id = b WHERE 100 * c >= 75 * (p.n + q.n - c)),
r(a, b) AS (SELECT doc_id, doc_id FROM n UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a),
m AS (SELECT a AS doc_id, min(b) AS component_id FROM r GROUP BY a)
SELECT doc_id, n AS n_shingles, component_id, doc_id = component_id AS kept FROM n JOIN m USING (doc_id)
"""
