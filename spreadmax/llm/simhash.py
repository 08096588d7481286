"""Near duplicates by 64-bit similarity fingerprints and a byte-position index.

Fingerprints that differ in at most 3 bits differ in at most 3 of their 8 bytes,
so at least 5 positional bytes are shared. Of the 8 triples of positions that
lie within one half of the word, at least one is then shared whole (5 shared
positions put 3 into one half). The index lists fingerprints by such triples.
Within a list every other position has postings (byte -> members); postings of
a fingerprint are tallied, members whose tally together with the triple reaches
5 are retained, and only they are verified by counting differing bits. A list
yields a spanning forest of its links, never all pairs of a group of copies.

Lists beyond `LIST_ROWS` fingerprints are split by two further positions (two
linked fingerprints of a triple share at least two of the five others), so that
membership itself is the tally of 5. What is still beyond the bound agrees in
40 bits; the other 24 are cut into 8 parts of 3 bits, of which at least 5 are
shared, and lists by 5 parts hold 512 fingerprints at most. So no task ever
holds a list beyond the bound, whatever the size of the corpus.

Defined cases: a null text counts as empty; texts without words have the
fingerprint zero, which links like any other; equal texts and equal
fingerprints are one class; documents without an id get the component of their
class (null if no id is in it); an empty table gives an empty result; further
columns of the input keep their names and values in `one_of_each`.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spreadmax.llm.common import append_columns, fold_bytes, text_bytes
from spreadmax.operators.connectivity import contracted_components
from spreadmax.session import written

BITS_APART = 3
SHARED_BYTES = 5
SHINGLE = 3
LIST_ROWS = 4096
SEED = 42
TRIPLES = [*combinations(range(4), 3), *combinations(range(4, 8), 3)]
_FEW = np.array([bin(b).count("1") for b in range(256)], np.uint8)


def fingerprint(text: bytes, size: int = SHINGLE) -> int:
    words = fold_bytes(text).split()
    n = len(words)
    if not n:
        return 0
    digest = xxhash.xxh64_intdigest
    if n <= size:
        return digest(b" ".join(words), SEED)
    shingles = map(b" ".join, zip(*(words[i:] for i in range(size)), strict=False))
    total = np.zeros(64, np.int64)
    n = n - size + 1
    done = 0
    while done < n:  # in blocks, so that very long texts need no more memory
        step = min(n - done, 1 << 16)
        hashes = np.fromiter((digest(next(shingles), SEED) for _ in range(step)), np.uint64, step)
        total += _bit_sums(hashes)
        done += step
    return int(np.packbits(2 * total > n).view(">u8")[0])


_LOW = np.uint64(0x0101010101010101)


def _bit_sums(hashes: np.ndarray) -> np.ndarray:
    """How many of the hashes have each bit, highest bit first.

    Bit k of all bytes is added up in the eight byte lanes of a word at once; a
    lane holds sums up to 255, so 255 words are added before lanes are opened.
    """
    n = len(hashes)
    if n <= 16:
        return np.unpackbits(hashes.astype(">u8").view(np.uint8)).reshape(n, 64).sum(axis=0, dtype=np.int64)
    starts = np.arange(0, n, 255)
    sums = np.empty((8, 8), np.int64)  # byte from the highest, bit from the highest
    for k in range(8):
        lanes = np.add.reduceat((hashes >> np.uint64(7 - k)) & _LOW, starts)
        sums[:, k] = lanes.astype(">u8").view(np.uint8).reshape(-1, 8).sum(axis=0, dtype=np.int64)
    return sums.reshape(-1)


def with_fingerprint(docs: DataFrame, name: str = "fp") -> DataFrame:
    def maker():
        def step(texts):
            return [np.array([fingerprint(t) for t in text_bytes(texts)], np.uint64).view(np.int64)]

        return step

    return append_columns(docs, ["text"], [(name, T.LongType())], maker)


def _tallied(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Positional bytes that each pair shares."""
    tally = np.zeros(len(a), np.uint8)
    for p in range(8):
        tally += a.view(np.uint8)[p::8] == b.view(np.uint8)[p::8]
    return tally


def _linked(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Numbers of the pairs that are retained by their tally and verified."""
    retained = np.flatnonzero(_tallied(a, b) >= SHARED_BYTES)
    return retained[np.bitwise_count(a[retained] ^ b[retained]) <= BITS_APART]


def _forest(members: np.ndarray, positions: tuple[int, ...] | list[int], need: int) -> list[tuple[int, int]]:
    """Spanning links of distinct fingerprints, breadth-first: each tallies its postings at `positions`;
    members with `need` shared bytes that are not yet reached are verified."""
    n = len(members)
    columns = members.view(np.uint8).reshape(n, 8)  # the lowest byte first
    postings = []
    for p in positions if need > 0 else ():
        order = np.argsort(columns[:, p], kind="stable")
        postings.append((p, order, np.searchsorted(columns[order, p], np.arange(257))))
    left = np.ones(n, bool)
    links: list[tuple[int, int]] = []
    for root in range(n):
        if not left[root]:
            continue
        left[root] = False
        queue = [root]
        while queue:
            at = queue.pop()
            if postings:
                tally = np.zeros(n, np.uint8)
                for p, order, starts in postings:
                    byte = columns[at, p]
                    tally[order[starts[byte] : starts[byte + 1]]] += 1
                retained = np.flatnonzero((tally >= need) & left)
            else:
                retained = np.flatnonzero(left)
            near = retained[np.bitwise_count(members[retained] ^ members[at]) <= BITS_APART]
            if len(near):
                left[near] = False
                links += [(int(members[at]), int(members[x])) for x in near]
                queue += near.tolist()
    return links


def _groups(batches):
    """(key, fingerprints) of consecutive rows with equal keys, across batches; several short lists come together."""
    key = fps = None
    for batch in batches:
        k = batch.column(0).to_numpy(zero_copy_only=False)
        f = batch.column(1).to_numpy(zero_copy_only=False).view(np.uint64)
        if key is not None:
            k, f = np.concatenate((key, k)), np.concatenate((fps, f))
        if not len(k):
            continue
        last = int(np.searchsorted(k, k[-1]))
        if last:
            yield k[:last], f[:last]
        key, fps = k[last:], f[last:]
    if key is not None and len(key):
        yield key, fps


def _links(batches, others=None):
    """Links within lists of sorted (key, fp) rows. `others`: the positions beside the three of a key; without it, keys hold 5."""
    for keys, fps in _groups(batches):
        starts = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
        sizes = np.diff(np.append(starts, len(keys)))
        src, dst = [], []
        for d in range(1, 8):  # short lists: all their pairs at once, at most 28 each
            short = np.repeat((sizes > d) & (sizes <= 8), sizes)
            at = np.flatnonzero(short[:-d] & (keys[d:] == keys[:-d])) if len(keys) > d else np.zeros(0, int)
            near = at[_linked(fps[at], fps[at + d])]
            src.append(fps[near])
            dst.append(fps[near + d])
        for a, n in zip(starts[sizes > 8], sizes[sizes > 8], strict=True):
            members = np.ascontiguousarray(fps[a : a + n])
            pairs = _forest(members, (), 0) if others is None else _forest(members, others(int(keys[a])), SHARED_BYTES - 3)
            if pairs:
                both = np.array(pairs, np.uint64)
                src.append(both[:, 0])
                dst.append(both[:, 1])
        src, dst = np.concatenate(src), np.concatenate(dst)
        if len(src):
            yield pa.RecordBatch.from_arrays([pa.array(src.view(np.int64)), pa.array(dst.view(np.int64))], names=["src", "dst"])


def _index(fps: DataFrame, subsets: list[tuple[int, ...]]) -> DataFrame:
    """(key, fp) rows for every subset of positions; keys of different subsets differ in their top byte's number."""
    packed = []
    for i, positions in enumerate(subsets):
        key = F.lit(i)
        for p in positions:
            key = F.shiftleft(key.cast("long"), 8).bitwiseOR(F.shiftrightunsigned("fp", 8 * p).bitwiseAND(F.lit(255)))
        packed.append(key.cast("long"))
    return fps.select(F.explode(F.array(*packed)).alias("key"), "fp")


def _sized(listed: DataFrame) -> DataFrame:
    """Lists of two fingerprints or more, with n, their number."""
    return listed.join(listed.groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter("n > 1"), "key")


def _searched(listed: DataFrame, others=None) -> DataFrame:
    rows = listed.select("key", "fp").repartition("key").sortWithinPartitions("key", "fp")
    return rows.mapInArrow(lambda batches: _links(batches, others), "src long, dst long")


#: Keys of five positions, for each triple its ten; the number of one is in bits 40 and up of a key.
FIVES = [(*t, *two) for t in TRIPLES for two in combinations([p for p in range(8) if p not in t], 2)]


def links_of(fps: DataFrame, list_rows: int = LIST_ROWS) -> DataFrame:
    """Distinct (fp) -> (src, dst): links that connect exactly the fingerprints which the 3-bit rule connects."""
    rest = [[p for p in range(8) if p not in t] for t in TRIPLES]
    sized = _sized(written(_index(fps, TRIPLES), "index"))
    # long lists never reach a task of this pass; the finer index below has them
    links = _searched(sized.filter(F.col("n") <= list_rows), lambda key: rest[key >> 24])
    large = sized.filter(F.col("n") > list_rows).select("key", "fp")
    if not large.limit(1).count():
        return links
    finer = None
    for i in range(len(TRIPLES)):
        own = _index(large.filter(F.shiftright("key", 24) == i).select("fp"), FIVES[10 * i : 10 * i + 10])
        own = own.select((F.col("key") + F.lit((10 * i) << 40)).alias("key"), "fp")
        finer = own if finer is None else finer.unionByName(own)
    sized = _sized(written(finer, "index"))
    links = links.unionByName(_searched(sized.filter(F.col("n") <= list_rows)))
    crowded = sized.filter(F.col("n") > list_rows).select("key", "fp")
    if not crowded.limit(1).count():
        return links
    return links.unionByName(_searched(_sized(written(_by_parts(crowded), "index"))))


def _by_parts(crowded: DataFrame) -> DataFrame:
    """(key, fp) rows for five of the eight parts of the 24 bits that a key leaves open, with keys of their own."""
    free = F.array(*[F.array(*[F.lit(8 * p) for p in range(8) if p not in five]) for five in FIVES])
    byte = lambda k: f"(shiftrightunsigned(fp, open[{k}]) & 255L)"
    bits = F.expr(f"{byte(0)} | shiftleft({byte(1)}, 8) | shiftleft({byte(2)}, 16)")
    opened = crowded.withColumn("open", F.get(free, F.shiftright("key", 40).cast("int"))).select("key", "fp", bits.alias("bits"))
    part = lambda k: F.shiftright("bits", 3 * k).bitwiseAND(7)
    keys = [F.xxhash64("key", F.lit(i), *[part(k) for k in five]) for i, five in enumerate(combinations(range(8), 5))]
    return opened.select(F.explode(F.array(*keys)).alias("key"), "fp")


def near_duplicates(docs: DataFrame, list_rows: int = LIST_ROWS) -> DataFrame:
    """doc_id, fp (long), component_id: one row per document."""
    work = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    prints = written(with_fingerprint(work).select("doc_id", "fp"), "prints")
    classes = written(prints.groupBy("fp").agg(F.min("doc_id").alias("least")), "classes")
    parts = contracted_components(written(links_of(classes.select("fp"), list_rows), "links"))
    joined = classes.join(parts.select(F.col("id").alias("fp"), "label"), "fp", "left").withColumn(
        "label", F.coalesce("label", "fp")
    )
    least = joined.groupBy("label").agg(F.min("least").alias("component_id"))
    of_class = joined.join(least, "label").select("fp", "component_id")
    return prints.join(of_class, "fp").select("doc_id", "fp", "component_id")


def one_of_each(docs: DataFrame, list_rows: int = LIST_ROWS) -> DataFrame:
    """`docs` with one document of each component: the one with the smallest id.

    Rows without an id cannot be told apart and stay. Rows that repeat an id stay together.
    """
    kept = near_duplicates(docs, list_rows).filter("doc_id = component_id").select("doc_id").distinct()
    named = docs.join(kept, docs["doc_id"].cast("long") == kept["doc_id"], "left_semi")
    return named.unionByName(docs.filter("doc_id is null"))
