"""Near duplicates by order MinHash, verified by banded alignment.

A sketch samples the ``depth`` least of a document's word runs (of ``gram`` words, labelled by their occurrence) under
one of ``sketches`` hash functions, and keeps them in text order, so that it agrees between texts of small edit distance. Texts that
agree in a sketch share a bucket. Copies count as one text from the start.

A comparison is a link if the edit distance in words is at most (1 - ``least``) of the longer text; classes are the connected components of
all links. Of a text of n words with a share x of them edited, (1 - x) ** gram of the runs stay whole; with J the part that these are
of the runs of both texts, a sketch agrees about J ** depth of the time. At x = 0.2 (the limit itself, edits scattered evenly, the worst
case) J is 0.196 and one of 80 sketches agrees 95 times in 100, at x = 0.15 more than 99.

First each text is compared with the leader (the least node) that it shares most buckets with, so that a group of n similar texts needs about
n comparisons. Then every bucket that still holds texts of several groups is compared whole, in salted blocks: each pair of different
groups, in the first bucket that it shares, unless sizes or counts of words and word pairs prove it too far apart. No bucket is cut off. The
work of this last step grows with the square of a bucket, that of texts which share a long passage and are of different groups; only links leave it.

Defined cases: null texts and texts without words are in no class but their own row's; texts shorter than ``gram`` words are one
run; texts with the same words but other punctuation are linked; repeated rows and repeated ids fall in the class of their text; a class
is named by its least doc_id (null if it has none); an empty table gives an empty result; extra columns pass through.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .alignment import banded_distance
from .common import persisted, words
from .components import components

MIX = np.uint64(0x9E3779B97F4A7C15)


class WordHashes(dict):
    def __missing__(self, word: str) -> int:
        if len(self) > 500_000:
            self.clear()
        self[word] = value = xxhash.xxh64_intdigest(word)
        return value


def mix(x: np.ndarray) -> np.ndarray:
    """A finaliser that spreads every bit of x over all others."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def runs_of(hashes: np.ndarray, gram: int) -> np.ndarray:
    """A hash of each run of gram words; of all words, if there are fewer."""
    n = max(1, len(hashes) - gram + 1)
    total = np.zeros(n, dtype=np.uint64)
    for k in range(min(gram, len(hashes))):
        total = mix(total + MIX) ^ hashes[k : k + n]
    return mix(total)


def labelled(runs: np.ndarray) -> np.ndarray:
    """Runs with the number of their earlier occurrences hashed in."""
    order = np.argsort(runs, kind="stable")
    ranked = runs[order]
    new = np.concatenate([[True], ranked[1:] != ranked[:-1]])
    if new.all():
        return runs
    starts = np.flatnonzero(new)
    seen = np.empty(len(runs), dtype=np.uint64)
    seen[order] = np.arange(len(runs)) - np.repeat(starts, np.diff(np.append(starts, len(runs))))
    return np.where(seen > 0, mix(runs + seen * MIX), runs)


def sketch(hashes: np.ndarray, multipliers: np.ndarray, gram: int, depth: int) -> np.ndarray:
    """One key a hash function: the depth least labelled runs, in text order."""
    runs = runs_of(hashes, gram)
    values = multipliers[:, None] * labelled(runs)[None, :]
    values ^= values >> np.uint64(32)
    line, picked = np.arange(len(multipliers)), []
    for _ in range(min(depth, len(runs))):
        at = values.argmin(axis=1)
        picked.append(at)
        values[line, at] = np.iinfo(np.uint64).max
    keys = multipliers.copy()
    for at in np.sort(np.stack(picked), axis=0):
        keys = mix(keys + MIX) ^ runs[at]
    return mix(keys)


def text_key(text: Column) -> Column:
    return F.unhex(F.md5(text))


def sketched(docs: DataFrame, sketches: int, gram: int, depth: int, seed: int) -> DataFrame:
    """(digest, doc_id, keys, copies), one row a different text with words; doc_id is the least of its copies."""
    multipliers = np.random.default_rng(seed).integers(1, 2**63, sketches).astype(np.uint64) * np.uint64(2) + np.uint64(1)
    known = docs.filter(F.col("text").isNotNull()).select(F.col("doc_id").cast("long"), text_key(F.col("text")).alias("digest"), "text")

    def run(batches):
        memo = WordHashes()
        for batch in batches:
            keys = []
            for text in batch.column(2).to_pylist():
                found = words(text)
                if found:
                    hashes = np.fromiter(map(memo.__getitem__, found), dtype=np.uint64, count=len(found))
                    keys.append(sketch(hashes, multipliers, gram, depth).view(np.int64))
                else:
                    keys.append(None)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(keys, pa.list_(pa.int64()))], names=["doc_id", "digest", "keys"])

    made = known.mapInArrow(run, "doc_id long, digest binary, keys array<long>").filter(F.col("keys").isNotNull())
    return made.groupBy("digest").agg(F.min("doc_id").alias("doc_id"), F.first("keys").alias("keys"), F.count("*").alias("copies"))


def profiles(texts: DataFrame, bins: int = 256) -> DataFrame:
    """(node, text, size, bag) of (node, text): the number of words, and counts of words and of word pairs by hash, at most 255 each."""

    def run(batches):
        memo = WordHashes()
        for batch in batches:
            sizes, bags = [], []
            for text in batch.column(1).to_pylist():
                found = words(text)
                hashes = mix(np.fromiter(map(memo.__getitem__, found), dtype=np.uint64, count=len(found)))
                pairs = mix(hashes[:-1] + MIX) ^ hashes[1:]
                sizes.append(len(found))
                bags.append(np.minimum([np.bincount((h % np.uint64(bins)).astype(np.int64), minlength=bins) for h in (hashes, mix(pairs))], 255).astype(np.uint8).tobytes())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(sizes, pa.int32()), pa.array(bags, pa.binary())], names=["node", "text", "size", "bag"])

    return texts.select("node", "text").mapInArrow(run, "node long, text string, size int, bag binary")


def allowed(longer, least: float):
    """Most edits between similar texts, the longer of which has that many words."""
    return ((1 - least) * longer + 1e-9).astype(np.int64)


def perhaps(bags: np.ndarray, bag: np.ndarray, most: np.ndarray) -> np.ndarray:
    """Which of the texts with these bags can be ``most`` edits from one with this bag (each their own number). An edit takes and adds a word at
    most, and two word pairs at most; what a text has beyond the shared counts has to be taken or added."""
    half, left = bag.shape[-1] // 2, np.arange(len(bags))
    for part, edited in ((slice(0, half), 1), (slice(half, None), 2)):
        some, one = bags[left, part], bag[..., part] if bag.ndim == 1 else bag[left, part]
        larger = np.maximum(some.sum(axis=1, dtype=np.int32), one.sum(axis=-1, dtype=np.int32))
        left = left[larger - np.minimum(some, one).sum(axis=1, dtype=np.int32) <= edited * most[left]]
    return left


def aligned(a: list[str], b: list[str], least: float) -> bool:
    return banded_distance(a, b, int((1 - least) * max(len(a), len(b)) + 1e-9)) is not None


def verified(pairs: DataFrame, about: DataFrame, least: float) -> DataFrame:
    """The pairs (u, v) whose texts align. about: profiles()."""
    wide = lambda name: about.select(F.col("node").alias(name), *(F.col(c).alias(f"{c}_{name}") for c in ("text", "size", "bag")))
    both = pairs.join(wide("u"), "u").join(wide("v"), "v").select("u", "v", "text_u", "text_v", "size_u", "size_v", "bag_u", "bag_v")

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            su, sv = (np.asarray(batch.column(k)) for k in (4, 5))
            bu, bv = (np.frombuffer(b"".join(batch.column(k).to_pylist()), np.uint8).reshape(batch.num_rows, -1) for k in (6, 7))
            most = allowed(np.maximum(su, sv), least)
            fits = np.flatnonzero(np.abs(su - sv) <= most)
            fits = fits[perhaps(bu[fits], bv[fits], most[fits])]
            texts = batch.column(2), batch.column(3)
            kept = [k for k in fits.tolist() if aligned(words(texts[0][k].as_py()), words(texts[1][k].as_py()), least)]
            yield batch.select(["u", "v"]).take(pa.array(kept, pa.int64()))

    return both.mapInArrow(run, "u long, v long")


def gathered(docs: DataFrame, wanted: DataFrame, few: int) -> DataFrame:
    """(node, text) of the wanted (node, digest): found by a broadcast of the digests while they are at most ``few``, else by a shuffle."""
    small = wanted.count() <= few
    texts = docs.filter(F.col("text").isNotNull()).select(text_key(F.col("text")).alias("digest"), "text")
    found = texts.join(F.broadcast(wanted) if small else wanted, "digest")
    return found.groupBy("node").agg(F.first("text").alias("text"))


def buckets_of(nodes: DataFrame) -> DataFrame:
    """Rows (node, key, band, lead) of the buckets with two or more texts; their leader is the least node."""
    rows = nodes.select("node", F.posexplode("keys").alias("band", "key")).select("node", "key", "band")
    least = rows.groupBy("key").agg(F.count("*").alias("n"), F.min("node").alias("lead")).filter("n > 1").select("key", "lead")
    return rows.join(least, "key")


def placed(rows: DataFrame, groups: DataFrame | None) -> DataFrame:
    """rows with the group of their node as ``place``; a node without links is its own."""
    if groups is None:
        return rows.withColumn("place", F.col("node"))
    return rows.join(groups.select("node", F.col("component").alias("place")), "node", "left").withColumn("place", F.coalesce("place", "node"))


def cells(batches, names: list[str]):
    """Rows of sorted batches, one table for each run of equal values in the columns named."""
    held: list[pa.Table] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        ids = np.stack([batch.column(n).to_numpy(zero_copy_only=False) for n in names], axis=1)
        starts = [0, *(np.flatnonzero((ids[1:] != ids[:-1]).any(axis=1)) + 1).tolist(), len(ids)]
        for a, b in zip(starts[:-1], starts[1:]):
            if held and tuple(ids[a]) != last:
                yield pa.concat_tables(held)
                held = []
            held.append(pa.Table.from_batches([batch.slice(a, b - a)]))
            last = tuple(ids[a])
    if held:
        yield pa.concat_tables(held)


def inside(cell: pa.Table, least: float) -> tuple[list[int], list[int]]:
    """Links (us, vs) that join the groups of one cell: texts of its left side are compared with those of its right side (and, if it says so, with
    one another), unless the pair is of one group by now, has met in the bucket of an earlier band, or is proven apart by size or
    bags. Enough links to join what is similar, not all of them."""
    n = cell.num_rows
    node, place, size = (cell.column(c).to_numpy() for c in ("node", "place", "size"))
    left = cell.column("left").to_numpy(zero_copy_only=False)
    band, i, j = (cell.column(c)[0].as_py() for c in ("band", "i", "j"))
    within = i == j or (j < 0 and i == 0)
    keys = cell.column("keys").combine_chunks().flatten().to_numpy().reshape(n, -1)[:, :band]
    bags = np.frombuffer(b"".join(cell.column("bag").to_pylist()), np.uint8).reshape(n, -1)
    text, read = cell.column("text"), {}

    def words_of(k: int) -> list[str]:
        if k not in read:
            read[k] = words(text[k].as_py())
        return read[k]

    _, group = np.unique(place, return_inverse=True)
    us, vs = [], []
    others = np.argsort(size, kind="stable")  # so that texts of similar sizes stand together
    if not within:
        others = others[~left[others]]
    sizes = size[others]
    for k in np.flatnonzero(left).tolist():
        at = others[np.searchsorted(sizes, int(np.ceil(least * size[k] - 1e-6))) : np.searchsorted(sizes, size[k] / least + 1e-6, side="right")]
        at = at[~left[at] | (at > k)]
        at = at[group[at] != group[k]]
        at = at[~(keys[at] == keys[k]).any(axis=1)]
        most = allowed(np.maximum(size[at], size[k]), least)
        for o in at[perhaps(bags[at], bags[k], most)].tolist():
            if group[o] != group[k] and aligned(words_of(k), words_of(o), least):
                us.append(int(max(node[o], node[k])))
                vs.append(int(min(node[o], node[k])))
                group[group == group[o]] = group[k]
    return us, vs


def dealt(member: DataFrame, about: DataFrame, groups: DataFrame | None, block: int) -> DataFrame:
    """Rows (key, i, j, left, node, band, place) of the cells of all buckets that hold texts of several groups.

    Buckets of more than ``block`` texts, or 2,000 times as many words, are dealt into parts. Where one group has nearly all texts, its
    parts are the right sides of cells (i, -1) and all others the left side of each, so that only these few are repeated; else each two parts
    are a cell (i, j). So a bucket of any size is compared whole, by many tasks.
    """
    rows = placed(member.select("node", "key", "band"), groups).join(about.select("node", "size"), "node")
    held = rows.groupBy("key", "place").agg(F.count("*").alias("n"), F.sum("size").alias("words"))
    spans = held.groupBy("key").agg(F.count("*").alias("groups"), F.max_by("place", "n").alias("most"), F.max("n").alias("major"), F.sum("n").alias("n"), F.sum("words").alias("words")).filter("groups > 1")
    parts = F.ceil(F.greatest(F.col("n") / block, F.col("words") / (block * 2000))).cast("int")
    spans = spans.select("key", "most", parts.alias("parts"), (F.col("n") - F.col("major") <= block / 8).alias("few"))
    known = persisted(rows.drop("size").join(spans, "key"), "order-minhash-open")
    part = F.pmod(F.xxhash64("node", F.lit(7)), F.col("parts")).cast("int")
    aside = F.col("few") & (F.col("parts") > 1)
    left = F.col("place") != F.col("most")
    every = F.sequence(F.lit(0), F.col("parts") - 1)
    each = known.withColumn("part", part).withColumn("with", F.explode(F.when(aside & ~left, F.array("part")).otherwise(every)))
    i, j = F.when(aside, F.col("with")).otherwise(F.least("part", "with")), F.when(aside, F.lit(-1)).otherwise(F.greatest("part", "with"))
    celled = each.withColumn("i", i).withColumn("j", j)
    return celled.select("key", "i", "j", F.when(aside, left).otherwise(F.col("part") == F.col("i")).alias("left"), "node", "band", "place")


def unmet(member: DataFrame, nodes: DataFrame, about: DataFrame, groups: DataFrame | None, least: float, block: int) -> DataFrame:
    """Links (u, v) between texts that share a bucket and are of different groups so far."""
    rows = dealt(member, about, groups, block)
    full = rows.join(about.join(nodes.select("node", "keys"), "node"), "node").repartition("key", "i", "j").sortWithinPartitions("key", "i", "j")

    def run(batches):
        for cell in cells(batches, ["key", "i", "j"]):
            us, vs = inside(cell, least)
            yield pa.RecordBatch.from_arrays([pa.array(us, pa.int64()), pa.array(vs, pa.int64())], names=["u", "v"])

    return full.mapInArrow(run, "u long, v long")


def classes(docs: DataFrame, least: float = 0.8, gram: int = 5, sketches: int = 80, depth: int = 2, seed: int = 42, block: int = 2048, few: int = 250_000) -> DataFrame:
    """(digest, class_node, class_id, first_digest, texts, copies): one row a different text that has words.

    ``few`` says up to how many rows of a few numbers a table may be broadcast or kept in one partition; the classes are the same at any value.
    """
    nodes = persisted(sketched(docs, sketches, gram, depth, seed).withColumn("node", F.monotonically_increasing_id()), "order-minhash-nodes")
    member = persisted(buckets_of(nodes), "order-minhash-buckets")
    wanted = persisted(member.select("node").distinct().join(nodes.select("node", "digest"), "node"), "order-minhash-wanted")
    about = persisted(profiles(gathered(docs, wanted, few)), "order-minhash-texts")
    # Each text against the leader that it shares most buckets with: n - 1 comparisons join n similar texts.
    offers = member.filter("lead <> node").groupBy("node", "lead").agg(F.count("*").alias("times"))
    pairs = persisted(offers.groupBy(F.col("node").alias("u")).agg(F.max_by("lead", F.struct("times", -F.col("lead"))).alias("v")), "order-minhash-pairs")
    links = persisted(verified(pairs, about, least), "order-minhash-links")
    groups = None if links.isEmpty() else components(links, few=few)
    more = persisted(unmet(member, nodes, about, groups, least, block), "order-minhash-links")
    if not more.isEmpty():
        links = links.unionByName(more.distinct())
        groups = components(links, few=few)
    known = placed(nodes.select("node", "digest", "doc_id", "copies"), groups).withColumnRenamed("place", "class_node")
    known = persisted(known, "order-minhash-classes")
    order = F.struct(F.col("doc_id").isNull().alias("last"), F.col("doc_id"), F.col("digest"))
    # A table of its own, so that a class of very many texts can be split where it is joined back.
    named = persisted(known.groupBy("class_node").agg(F.min(order).alias("least"), F.count("*").alias("texts")), "order-minhash-named")
    return known.select("digest", "class_node", "copies").join(named, "class_node").select("digest", "class_node", F.col("least.doc_id").alias("class_id"), F.col("least.digest").alias("first_digest"), "texts", "copies")


def classified(docs: DataFrame, **options) -> DataFrame:
    """docs with the class of each row: class_id, texts (different texts of the class); null where it has no words."""
    known = classes(docs, **options)
    clear, known = docs.drop("class_id", "texts"), known.drop("copies", "first_digest")
    return clear.withColumn("_digest", text_key(F.col("text"))).join(known.withColumnRenamed("digest", "_of"), F.col("_digest") == F.col("_of"), "left").drop("_of")


def near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """doc_id and class_id of every row; a row without words is its own class."""
    found = classified(docs.select("doc_id", "text"), **options)
    own = F.when(F.col("class_node").isNull(), F.col("doc_id")).otherwise(F.col("class_id"))
    return found.select("doc_id", own.alias("class_id"), F.coalesce("texts", F.lit(1)).alias("texts"))


def deduplicated(docs: DataFrame, few: int = 250_000, **options) -> DataFrame:
    """One row of each class: of its text with the least doc_id, a row with that id. Rows without words all stay.

    Only texts with copies or of classes of several texts need a decision; they are joined to the rows, by a broadcast while they are
    few by count, so that most texts stay where they are.
    """
    names = docs.columns
    known = classes(docs.select("doc_id", "text"), few=few, **options)
    affected = persisted(known.filter("texts > 1 or copies > 1").select(F.col("digest").alias("_of"), (F.col("digest") == F.col("first_digest")).alias("_first"), F.col("class_id").alias("_keep"), F.col("copies").alias("_copies")), "order-minhash-affected")
    affected = F.broadcast(affected) if affected.count() <= few else affected
    keyed = docs.select(text_key(F.coalesce("text", F.lit(""))).alias("_digest"), F.struct(*names).alias("_row"))
    met = keyed.join(affected, F.col("_digest") == F.col("_of"), "left")
    clear = met.filter(F.col("_of").isNull() | (F.col("_first") & (F.col("_copies") == 1)))
    same = met.filter(F.col("_first") & (F.col("_copies") > 1) & F.col("_row.doc_id").eqNullSafe(F.col("_keep")))
    once = same.groupBy("_digest").agg(F.min("_row").alias("_row"))
    return clear.select("_row.*").unionByName(once.select("_row.*"))
