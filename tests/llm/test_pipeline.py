"""Every stage, and run(), against a brute-force reading: which documents stay, how often, and where they go."""

import hashlib
import inspect
import math
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

import corpus_pipeline
from spreadmax.llm import mixing, toxicity
from spreadmax.llm.common import table
from tests.llm.test_operators import _components, _fingerprint, vocabulary, words

STAGES = dict(corpus_pipeline.STAGES)
COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def corpus(spark, tmp_path_factory):
    """Documents with toxic ones, copies, benchmark passages, nulls, ties and empty texts."""
    rng, v = random.Random(21), vocabulary(21)
    line = lambda n: " ".join(rng.choice(v) for _ in range(n))
    items = [("a", line(40)), ("b", line(20)), ("c", "short item"), ("d", None)]
    docs, labels = [], []
    for i in range(260):
        text = line(rng.randint(5, 60))
        if i % 6 == 1:
            text += " vileword " + rng.choice(v)
        docs.append([i, text])
        if i % 3:
            labels.append((i, 1, int(i % 6 == 1)))
    for i in range(260, 290):  # copies, near copies and texts that only differ in case
        base = docs[rng.randrange(0, 250)][1]
        docs.append([i, base if i % 3 == 0 else base.upper() if i % 3 == 1 else base + " " + rng.choice(v)])
    docs += [[300, items[0][1]], [301, "Intro: " + items[0][1].upper() + ". end"], [302, line(500) + " " + " ".join(items[1][1].split()[:13])], [303, "short, ITEM"]]
    docs += [[310, None], [311, ""], [312, "  \n"], [None, "a text without an id"], [None, "a text without an id"], [7, docs[7][1]], [320, line(9000)]]
    rows = [(i, t, ["en", "de", None][(i or 0) % 3], ["big", "big", "big", "small", None][(i or 0) % 5], None if t is None else len(t)) for i, t in docs]
    place = str(tmp_path_factory.mktemp("corpus"))
    spark.createDataFrame(rows, COLUMNS).write.parquet(f"{place}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{place}/labels.parquet")
    spark.createDataFrame(items, "item_id string, text string").write.parquet(f"{place}/benchmark.parquet")
    return place, rows, labels, items


def rows_of(df):
    return [tuple(r) for r in df.collect()]


def kept_by_toxicity(spark, place, rows, labels):
    net, inner = toxicity.fit_toxicity(table(spark, place, "documents"), table(spark, place, "labels"))
    score = [float(toxicity.Scorer(net).score([(t or "").encode()])[0]) for _, t, *_ in rows]
    truth = {i: y for i, _, y in labels if zlib.crc32(str(i).encode()) % 5 != 0}
    cuts = {}
    for lang in ("en", "de"):
        seen = {r[0]: (inner.get(r[0], s), truth[r[0]]) for r, s in zip(rows, score, strict=True) if r[2] == lang and r[0] in truth}
        if min(sum(y == k for _, y in seen.values()) for k in (0, 1)) < toxicity.LEAST:
            continue
        bins = defaultdict(list)
        for s, y in seen.values():
            odds = max(-toxicity.ODDS, min(toxicity.ODDS, math.log(s / (1 - s)) if 0 < s < 1 else math.copysign(99, s - 0.5)))
            bins[math.floor(odds * toxicity.BINS)].append((s, y))
        best, order = None, sorted(bins, reverse=True)
        for k, _ in enumerate(order):  # all above a bin's lower end go
            cost = sum(-1 if y else 2 for b in order[: k + 1] for _, y in bins[b])
            if best is None or cost < best[0]:
                below = max((s for s, _ in bins[order[k + 1]]), default=0) if k + 1 < len(order) else 0
                best = (cost, (min(s for s, _ in bins[order[k]]) + below) / 2)
        cuts[lang] = best[1] if best[0] <= 0 else 2.0
    return [r for r, s in zip(rows, score, strict=True) if s < cuts.get(r[2], 0.5)]


def kept_by_dedup(rows):
    roots = _components([_fingerprint(r[1]) for r in rows])
    least = {}
    for r, root in zip(rows, roots, strict=True):
        if r[0] is not None:
            least[root] = min(r[0], least.get(root, r[0]))
    return [r for r, root in zip(rows, roots, strict=True) if r[0] is None or r[0] == least[root]]


def kept_by_decontamination(rows, items):
    windows = [w[i : i + 13] for _, t in items for w in [words(t)] if w for i in range(max(1, len(w) - 12))]
    out = []
    for r in rows:
        w, hit = words(r[1]), set()
        for g in windows:
            for k in range(len(w) - len(g) + 1):
                if w[k : k + len(g)] == g:
                    hit.update(range(k, k + len(g)))
        if not (hit and 20 * len(hit) >= len(w)):
            out.append(r)
    return out


def copies_by_mixing(rows):
    size = Counter()
    for r in rows:
        size[r[3]] += len((r[1] or "").encode()) + 1
    target = {s: n**mixing.FLATTEN for s, n in size.items()}
    out = Counter()
    for r in rows:
        rate = target[r[3]] / sum(target.values()) * sum(size.values()) / size[r[3]]
        parts = max(1, math.ceil(rate / mixing.PART))
        name = str(r[0]) if r[0] is not None else hashlib.md5((r[1] or "").encode()).hexdigest()
        for j in range(1, parts + 1):
            u = int(hashlib.md5(f"{mixing.SEED}:{j}:{name}".encode()).hexdigest()[:12], 16) / (1 << 48)
            p = upto = math.exp(-rate / parts)
            n = 0
            while upto <= u and n < mixing.STEPS:
                n += 1
                p *= rate / parts / n
                upto += p
            out[r] += n
    return +out


def same(got, want):
    assert Counter(map(str, got)) == Counter(map(str, want))


def test_stages_equal_brute_force(spark, corpus):
    place, rows, labels, items = corpus
    frame = lambda x: spark.createDataFrame(x, COLUMNS)
    assert list(STAGES) == ["toxicity", "near_dedup", "decontamination", "mixing", "sharding"]
    assert all(list(inspect.signature(f).parameters) == ["spark", "docs", "sf_dir"] for f in STAGES.values())
    clean = kept_by_toxicity(spark, place, rows, labels)
    same(rows_of(STAGES["toxicity"](spark, table(spark, place, "documents"), place)), clean)
    truth = {i: y for i, _, y in labels}
    assert sum(truth.get(r[0], 0) for r in clean) <= 2 and len(clean) >= len(rows) - sum(" vileword " in (r[1] or "").lower() for r in rows) - 2
    unique = kept_by_dedup(clean)
    same(rows_of(STAGES["near_dedup"](spark, frame(clean), place)), unique)
    own = kept_by_decontamination(unique, items)
    same(rows_of(STAGES["decontamination"](spark, frame(unique), place)), own)
    assert len(own) < len(unique) < len(clean) < len(rows)
    mixed = list(copies_by_mixing(own).elements())
    same(rows_of(STAGES["mixing"](spark, frame(own), place)), mixed)
    dealt = STAGES["sharding"](spark, frame(mixed), place).collect()
    check_shards(dealt, mixed)
    check_shards(corpus_pipeline.run(spark, place).collect(), mixed)


def check_shards(dealt, mixed):
    text = lambda r: (r[1] or "").encode()
    want = [(r[0], len(text(r)) + 1, zlib.crc32(text(r))) for r in mixed]
    same([(r["doc_id"], r["size"], r["text_crc32"]) for r in dealt], want)
    shards = defaultdict(list)
    group = defaultdict(list)
    for r in dealt:
        shards[r["shard"]].append(r["slot"])
        group[r["size"], r["text_crc32"]].append(r["shard"])
    sizes = [len(shards[s]) for s in range(8)]
    assert max(sizes) - min(sizes) <= 1 and all(sorted(x) == list(range(len(x))) for x in shards.values())
    for r in dealt:  # links to documents of other shards, by counting
        own = group[r["size"], r["text_crc32"]]
        assert r["links_cut"] == len(own) - own.count(r["shard"])


def test_tables_without_rows(spark, corpus, tmp_path):
    place, _, labels, items = corpus
    spark.createDataFrame([], COLUMNS).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([], "item_id string, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
    for stage in STAGES.values():
        assert stage(spark, table(spark, str(tmp_path), "documents"), place).count() == 0


def test_given_tables(spark, small):
    """On the given tables every filter takes some documents, few of them clean."""
    docs = table(spark, small, "documents")
    before = docs.count()
    after = STAGES["toxicity"](spark, docs, small)
    toxic = {r[0]: r[1] for r in table(spark, small, "labels").select("doc_id", "toxic").collect()}
    kept = [r["doc_id"] for r in after.select("doc_id").collect()]
    gone = {r["doc_id"] for r in docs.select("doc_id").collect()} - set(kept)
    assert 0 < len(kept) < before and np.mean([toxic.get(i, 0) == 0 for i in gone]) < 0.9
