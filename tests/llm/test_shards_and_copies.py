"""Operators 8 and 10 against brute force."""

import random
import zlib

from widefeat.llm.common import read_table
from widefeat.llm.queries import queries
from widefeat.llm.sharding import shard_by_bytes
from widefeat.llm.simhash import Ring, connect, fingerprint, linked, near_duplicates, signed

ODD = [(0, None, "x"), (1, "", "x"), (2, " \t\n", "x"), (3, "One two", "x"), (4, "one TWO", "x"), (None, "no id at all here", "x"), (6, "a b c d e", "x"), (6, "a b c d e", "x"), (7, "É b " * 30_000, "x")]
SCHEMA = "doc_id long, text string, component_id string"


def check_shards(rows, got, shards=8):
    got = sorted(got, key=lambda r: (r.shard, r.slot))
    assert [(r.doc_id is not None, r.doc_id) for r in got] == sorted((d is not None, d) for d, _ in rows)
    sizes = {}
    for k in range(shards):
        own = [r for r in got if r.shard == k]
        assert [r.slot for r in own] == list(range(len(own)))
        sizes[k] = sum(r.size for r in own)
    total, largest = sum(sizes.values()), max((r.size for r in got), default=0)
    assert all(abs(s - total / shards) <= largest for s in sizes.values())
    want = sorted((len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for _, t in rows)
    assert sorted((r.size, r.text_crc32) for r in got) == want
    assert {(r.law, r.grown_shard) for r in got} <= {("bytes", None)}


def test_op8(spark, small_dir):
    docs = read_table(spark, small_dir, "documents").select("doc_id", "text")
    check_shards([tuple(r) for r in docs.collect()], queries()["op8_byte_shards"](spark, small_dir).collect())
    odd = spark.createDataFrame(ODD, SCHEMA)
    check_shards([r[:2] for r in ODD], shard_by_bytes(odd).collect())
    assert shard_by_bytes(odd.limit(0)).count() == 0


def brute_fingerprint(text):
    from xxhash import xxh64_intdigest

    words = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    for blank in "\t\n\x0b\x0c\r":
        words = words.replace(blank, " ")
    words = [w for w in words.split(" ") if w]
    grams = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or ([" ".join(words)] if words else [])
    hashes = [xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_components(nodes, links):
    parent = {n: n for n in nodes}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = sorted((find(a), find(b)))
        parent[b] = a
    return {n: find(n) for n in nodes}


def brute_near(fps):
    fps = list(fps)
    return [(a, b) for i, a in enumerate(fps) for b in fps[i + 1 :] if bin(a ^ b).count("1") <= 2]


def test_fingerprint():
    rnd = random.Random(5)
    for text in [None, "", "A b", *(" ".join(rnd.choice(["Alpha", "beta", "Ñandú", "x\ty", "ß z"]) for _ in range(rnd.randint(1, 90))) for _ in range(40))]:
        assert fingerprint(text) == signed(brute_fingerprint(text))


def test_ring_is_complete():
    """Every pair within the distance has a chain that keeps all its budgets."""
    rnd = random.Random(1)
    for segments, most in ((7, 2), (5, 2), (9, 2), (8, 3), (4, 1)):
        ring = Ring(segments, most)
        for _ in range(300):
            x = sum(1 << b for b in rnd.sample(range(64), rnd.randint(0, most)))
            assert any(all(bin(x & ring.chain(i, k)).count("1") <= k * most // segments for k in range(1, segments + 1)) for i in range(segments))


def same_partition(a, b):
    return len({*zip(a, b, strict=True)}) == len(set(a)) == len(set(b))


def test_links_connect_dense_and_sparse_groups(spark):
    rnd = random.Random(2)
    fps = {rnd.getrandbits(64) for _ in range(150)}
    for centre in list(fps)[:6]:
        for _ in range(60):
            x = centre
            for b in rnd.sample(range(64), rnd.randint(1, 4)):
                x ^= 1 << b
            fps.add(x)
    want = brute_components(fps, brute_near(fps))
    distinct = spark.createDataFrame([(signed(x),) for x in fps], "fp long")
    labels = {r.node: r.label for r in connect(linked(distinct)).collect()}
    order = sorted(fps)
    assert same_partition([want[x] for x in order], [labels.get(signed(x), signed(x)) for x in order])
    three = brute_components(fps, [(a, b) for i, a in enumerate(order) for b in order[i + 1 :] if bin(a ^ b).count("1") <= 3])
    labels = {r.node: r.label for r in connect(linked(distinct, most_bits=3, segments=10)).collect()}
    assert same_partition([three[x] for x in order], [labels.get(signed(x), signed(x)) for x in order])


def check_documents(rows, got):
    fps = {}
    for doc_id, text in rows:
        fps.setdefault(brute_fingerprint(text), []).append(doc_id)
    label = brute_components(sorted(fps), brute_near(sorted(fps)))
    least = {}
    for fp, ids in fps.items():
        known = [i for i in ids if i is not None]
        if known:
            least[label[fp]] = min(least.get(label[fp], known[0]), *known)
    want = sorted((str(doc_id), fp, least.get(label[fp])) for fp, ids in fps.items() for doc_id in ids)
    assert sorted((str(r.doc_id), r.fp % (1 << 64), r.component_id) for r in got) == want


def test_op10(spark, mid_dir):
    docs = read_table(spark, mid_dir, "documents").select("doc_id", "text")
    check_documents([tuple(r) for r in docs.collect()], near_duplicates(docs).collect())
    odd = spark.createDataFrame(ODD, SCHEMA)
    check_documents([r[:2] for r in ODD], near_duplicates(odd).collect())
    assert near_duplicates(odd.limit(0)).count() == 0
    row = queries()["op10_pigeonring_simhash"](spark, mid_dir).first()
    assert len(row.fingerprint) == 16 and row.component_id <= row.doc_id
