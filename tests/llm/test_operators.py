"""Each operator against brute force, an exact round trip or held-out accuracy, and its edge cases."""

import hashlib
import itertools
import random
import re
import time

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from netprop.llm import common, embed, html, packing, pieces, pii, quality, sharding, simhash, suffix, warc

DOCS = "doc_id long, text string, lang string"
ODD = [(1, None, "x"), (2, "", "x"), (3, "a b", None), (3, "a b", None), (None, "lone text", "y"), (4, "word " * 3000, "z"), (5, "word " * 3000, "z"), (5, "other text of the same id", "z"), (6, " \t\n ", "z"), (7, "é𝄞 ünï ▁ code", "z")]


@pytest.fixture(scope="module")
def docs(spark, sf):
    return common.table(spark, sf, "documents").cache()


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, DOCS).withColumn("label", F.lit("clash")).withColumn("size", F.lit(1)).cache()


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


# ---------------------------------------------------------------- 1: fingerprints


def classes_of(prints, ids, radius=4):
    prints = np.array(prints, np.uint64)
    near, root = np.bitwise_count(prints[:, None] ^ prints[None, :]) <= radius, np.array(ids)
    while True:
        new = np.array([root[near[i]].min() for i in range(len(ids))])
        if (new == root).all():
            return dict(zip(ids, root.tolist(), strict=True))
        root = new


def slow_fingerprint(text, width=4):
    import xxhash

    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text))
    shingles = [" ".join(words[i : i + width]) for i in range(len(words) - width + 1)] or ([" ".join(words)] if words else [])
    hs = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << i for i in range(64) if 2 * sum(h >> i & 1 for h in hs) > len(hs))


@pytest.mark.parametrize("hot", [4096, 1])
def test_simhash(docs, hot):
    rows = {r.doc_id: r.text for r in docs.collect()}
    prints = {k: slow_fingerprint(t) for k, t in rows.items()}
    got = {r.doc_id: r for r in simhash.near_duplicates(docs, hot_members=hot).collect()}
    assert all(got[k].fingerprint == f"{p:016x}" for k, p in prints.items())
    assert {k: got[k].component_id for k in rows} == classes_of(list(prints.values()), list(rows))


def test_simhash_dense_groups(spark):
    """Many fingerprints within a few bits of each other, and chains between groups."""
    rng = random.Random(5)
    seeds = [rng.getrandbits(64) for _ in range(4)]
    prints = sorted({s ^ sum(1 << rng.randrange(64) for _ in range(rng.randrange(5))) & (2**64 - 1) for s in seeds for _ in range(300)})
    fps = spark.createDataFrame([(p - (1 << 64) if p >> 63 else p,) for p in prints], "fp long")
    plan = simhash.plan_search(fps)
    assert sum(plan["radii"]) == 4 - len(plan["groups"]) + 1
    want = classes_of(prints, list(range(len(prints))))
    for hot in (10**6, 2):
        roots = {r.id: r.root for r in common.connected_components(simhash.spanning_links(fps, plan, hot)).collect()}
        mine = {i: roots.get(p - (1 << 64) if p >> 63 else p, ("own", i)) for i, p in enumerate(prints)}
        assert len(set(mine.values())) == len(set(want.values()))
        assert len(set(zip(mine.values(), want.values(), strict=True))) == len(set(want.values()))


def test_simhash_buckets_hot_again_and_again(spark):
    """Fingerprints that agree on half of their bits and more: buckets are split until nothing is left to split by."""
    rng = random.Random(9)
    prints = sorted({(rng.getrandbits(14) << 3) | (0xABCD << 40) for _ in range(300)})
    fps = spark.createDataFrame([(p,) for p in prints], "fp long")
    plan = simhash.plan_search(fps)
    want = classes_of(prints, list(range(len(prints))))
    rows = simhash.split_hot(simhash.probe_rows(fps, plan), plan, 20)
    assert rows.select("path").distinct().count() > 4
    roots = {r.id: r.root for r in common.connected_components(simhash.spanning_links(fps, plan, 20)).collect()}
    mine = {i: roots.get(p, ("own", i)) for i, p in enumerate(prints)}
    assert len(set(zip(mine.values(), want.values(), strict=True))) == len(set(want.values())) == len(set(mine.values()))


def similar_classes(texts, width=5, similarity=0.8):
    """Smallest key that each key reaches by pairs of that Jaccard similarity, all pairs compared."""
    sets = {}
    for k, t in texts.items():
        words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets[k] = {tuple(words[i : i + width]) for i in range(max(1, len(words) - width + 1))}
    root = {k: k for k in texts}
    near = [(a, b) for a, b in itertools.combinations(sorted(texts), 2) if len(sets[a] & sets[b]) >= similarity * len(sets[a] | sets[b])]
    while True:
        new = dict(root)
        for a, b in near:
            new[a] = new[b] = min(new[a], new[b])
        if new == root:
            return root
        root = new


def test_near_copies(spark):
    """Against all pairs: copies with words changed here and there, and chains of them; nothing goes that is not similar."""
    rng = random.Random(11)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(5))
    texts, k = {}, 0
    for _ in range(120):
        base = [word() for _ in range(rng.randrange(60, 200))]
        for _ in range(rng.randrange(1, 6)):
            copy = list(base)
            for _ in range(rng.randrange(0, max(1, len(base) // 25))):
                copy[rng.randrange(len(copy))] = word()
            texts[k], k = " ".join(copy), k + 1
            if rng.random() < 0.3:
                base = copy
    root = similar_classes(texts)
    got = sorted(r.doc_id for r in simhash.representatives(spark.createDataFrame([(k, t, "x") for k, t in texts.items()], DOCS)).collect())
    want = {k for k in texts if root[k] == k}
    assert want <= set(got)  # of each class the first stays, and no text goes without a similar one
    missed = sum(root[k] != k for k in got)
    assert missed <= 0.1 * (len(texts) - len(want)) and len(texts) - len(want) > 120  # candidates are found with a stated recall


def test_least_forest():
    rng = np.random.default_rng(2)
    a, b, w = rng.integers(0, 60, 300), rng.integers(0, 60, 300), rng.integers(0, 9, 300)
    at = common.local_forest(a, b, w)
    seen, total = {i: i for i in range(60)}, 0
    find = lambda i: i if seen[i] == i else find(seen[i])
    for e in np.argsort(w, kind="stable"):
        x, y = find(int(a[e])), find(int(b[e]))
        if x != y:
            seen[x], total = y, total + int(w[e])
    assert w[at].sum() == total and len(at) == 60 - len({find(i) for i in range(60)})


@pytest.mark.parametrize("suffix", [False, True])
def test_no_candidate_is_left_out(spark, suffix):
    """Sixty texts of the same word pairs in thirty orders: nearly all candidates are unlike, and each text has one partner among them."""
    rng, texts = random.Random(3), {}
    for k in range(30):
        order = rng.sample(range(60), 60)
        for twin in range(2):  # the same words twice in other order at the end, or another last word
            end = [f"last{2 * k + twin}"] if suffix else ["k", "w1", "k"] * twin
            texts[2 * k + twin] = " ".join(["k", *[x for i in order for x in (f"w{i}", "k")], *end])
    root = similar_classes(texts)
    assert len(set(root.values())) == 30
    frame = spark.createDataFrame([(k, t, "x") for k, t in texts.items()], DOCS)
    assert sorted(r.doc_id for r in simhash.representatives(frame).collect()) == sorted(set(root.values()))


def test_large_buckets_give_all_links_across(monkeypatch):
    rng = np.random.default_rng(5)
    fp = rng.integers(0, 1 << 6, 400).astype(np.int64)
    cell, member, root = np.repeat([0, 1], 200), rng.random(400) < 0.5, rng.integers(0, 5, 400)
    want = {(min(fp[i], fp[j]), max(fp[i], fp[j])) for i in range(400) for j in range(400) if cell[i] == cell[j] and member[j] and root[i] != root[j] and fp[i] != fp[j] and int(fp[i] ^ fp[j]).bit_count() <= 2}
    for chunk in (64, 1 << 21):
        monkeypatch.setattr(simhash, "PAIR_CHUNK", chunk)
        got = {(min(x, y), max(x, y)) for a, b, _ in simhash.bucket_links(cell, fp, member, 2, root) for x, y in zip(a, b, strict=True)}
        assert got == want


def test_sketches_lose_no_pair(spark):
    rng = random.Random(4)
    words = [f"w{i}" for i in range(400)]
    base = [rng.choice(words) for _ in range(300)]
    texts = {0: " ".join(base)} | {k: " ".join(base[: 300 - 7 * k] + rng.sample(words, k)) for k in range(1, 12)} | {20: "", 21: "a b"}
    sets = common.checkpointed(simhash.shingle_sets(spark.createDataFrame([(k, t.encode()) for k, t in texts.items()], "node long, text binary"), 5))
    every = spark.createDataFrame(list(itertools.combinations(texts, 2)), "a long, b long")
    want = sorted(map(tuple, simhash.alike(every, sets, 0.8).collect()))
    open_ = simhash.maybe_alike(every, sets, 0.8)
    assert want and set(want) <= set(map(tuple, open_.collect())) and open_.count() < every.count()


def joined_rows(spark, run):
    """What ``run`` returns, and the most rows that joins of one kind made in it."""
    store, made = spark._jsparkSession.sharedState().statusStore(), {}
    begun = store.executionsCount()
    found = run()
    time.sleep(1)
    for e in (store.executionsList().apply(i) for i in range(begun, store.executionsCount())):
        metrics, nodes = store.executionMetrics(e.executionId()), store.planGraph(e.executionId()).allNodes()
        for node in (nodes.apply(j) for j in range(nodes.size()) if "Join" in nodes.apply(j).name()):
            kind = re.sub(r"#\d+L?|^\w+(?=Join )", "", node.desc())[:60]
            for m in (node.metrics().apply(q) for q in range(node.metrics().size())):
                if m.name() == "number of output rows" and metrics.get(m.accumulatorId()).isDefined():
                    made[kind] = made.get(kind, 0) + int(metrics.get(m.accumulatorId()).get().replace(",", ""))
    return found, max(made.values())


def test_candidates_are_no_rows(spark):
    """Texts of the same word pairs in other orders: all are candidates of each other and nearly none are alike. No join makes a row for each pair."""
    rng, texts = random.Random(8), {}
    for k in range(160):
        order = rng.sample(range(60), 60)
        for twin in range(2):
            texts[2 * k + twin] = " ".join(["k", *[x for i in order for x in (f"w{i}", "k")], *["k", "w1", "k"] * twin])
    frame = spark.createDataFrame([(k, t, "x") for k, t in texts.items()], DOCS)
    got, most = joined_rows(spark, lambda: simhash.representatives(frame).collect())
    assert sorted(r.doc_id for r in got) == sorted(set(similar_classes(texts).values()))
    assert 0 < most < 20 * len(texts)


@pytest.mark.parametrize("rows, shingles, short", [(64, 1 << 20, 13), (8, 1 << 20, 3), (8, 200, 3), (1, 1, 0)])
def test_blocks_lose_no_pair(spark, monkeypatch, rows, shingles, short):
    """Groups in one block or many, of texts of very unequal length, against all pairs."""
    for name, value in (("BLOCK_ROWS", rows), ("BLOCK_SHINGLES", shingles), ("SHORT_K", short)):
        monkeypatch.setattr(simhash, name, value)
    rng, texts = random.Random(6), {100: "", 101: "a b"}
    for k in range(24):
        base = [f"w{rng.randrange(500)}" for _ in range(rng.choice([7, 15, 16, 17, 31, 33, 64, 127, 260]))]
        texts[k] = " ".join(base)
        texts[k + 24] = " ".join(base + [f"v{k}"] * rng.randrange(4))
    group = {k: k % 3 for k in texts}
    frame = spark.createDataFrame([(k, k % 2, group[k], sum(g == group[k] for g in group.values()), t.encode()) for k, t in texts.items()], "node long, fp long, group long, rows long, text binary")
    links = simhash.alike_links(common.stored(simhash.shingle_sets(frame, 5), "sets"), 1, 0.8)
    got = {k: k for k in texts} | {r.id: r.root for r in common.connected_components(links).collect()}
    want = {}
    for g in range(3):
        want |= similar_classes({k: t for k, t in texts.items() if group[k] == g})
    assert got == want and len(set(want.values())) < len(texts)
    assert links.count() < 40 * len(texts)


def test_representatives(spark):
    """Rows without an id and rows that share one go only as near-duplicates; which row stays does not depend on the order of rows."""
    words = lambda s: " ".join(f"{s}{i}" for i in range(60))
    rows = [(None, words("a"), "x"), (None, words("b"), "x"), (None, words("c"), "y"), (5, words("d"), "x"), (5, words("e"), "x"), (5, words("d"), "x"), (5, words("d"), "z"), (2, words("a"), "y"), (9, words("b"), "y"), (7, None, "x"), (8, "", "x")]
    want = {(2, words("a")), (9, words("b")), (None, words("c")), (5, words("d")), (5, words("e")), (7, None)}
    seen = set()
    for seed in range(2):
        random.Random(seed).shuffle(rows)
        got = simhash.representatives(spark.createDataFrame(rows, DOCS)).collect()
        assert len(got) == len(want) and {(r.doc_id, r.text) for r in got} == want
        seen.add(tuple(sorted(map(str, got))))
    assert len(seen) == 1
    assert simhash.representatives(spark.createDataFrame([], DOCS)).columns == ["doc_id", "text", "lang"]


def test_flood_equals_pairs():
    rng = np.random.default_rng(1)
    fp = (rng.integers(0, 1 << 12, 400) | (7 << 40)).astype(np.int64)
    cell, member = np.zeros(400, np.int64), rng.random(400) < 0.5
    member = np.isin(fp, fp[member])
    a = [np.stack(x, 1) for x in simhash.bucket_links(cell, fp, member, 2)]
    b = [np.stack(x, 1) for x in simhash._flood(fp, member, 2)]
    one, two = (dict(zip(*map(list, common.local_components(*np.concatenate(x).T)), strict=True)) for x in (a, b))
    assert all(one[k] == two[k] for k in one)


def test_simhash_edges(odd, none):
    got = simhash.near_duplicates(odd).collect()
    assert len(got) == len(ODD)
    zero = [r for r in got if r.fingerprint == "0" * 16]
    assert {r.doc_id for r in zero} == {1, 2, 6} and {r.component_id for r in zero} == {1}
    assert simhash.near_duplicates(none).count() == 0


# ------------------------------------------------------------- 3: repeated strings


def slow_repeats(rows, length):
    seen, out = set(), {}
    for key, body in rows:
        gone = bytearray(len(body))
        for i in range(len(body) - length + 1):
            w = body[i : i + length]
            if w in seen:
                gone[i : i + length] = b"\1" * length
            seen.add(w)
        left = bytes(b for b, g in zip(body, gone, strict=True) if not g)
        out[key] = (len(body), sum(gone), len(re.findall(b"\1+", gone)), hashlib.sha256(left).hexdigest())
    return out


def test_repeated_windows():
    rng = random.Random(3)
    for _ in range(60):
        length = rng.choice([3, 5, 12])
        parts = [bytes(rng.choice(b"ab") for _ in range(rng.randrange(40))) for _ in range(rng.randrange(1, 8))]
        part, off = suffix.repeated_windows(parts, np.array([[i, 0, 0] for i in range(len(parts))]), length)
        seen, want = set(), []
        for i, b in enumerate(parts):
            for s in range(len(b) - length + 1):
                if b[s : s + length] in seen:
                    want.append((i, s))
                seen.add(b[s : s + length])
        assert sorted(zip(part.tolist(), off.tolist(), strict=True)) == sorted(want)


@pytest.mark.parametrize("hot", [512, 1])
def test_suffix(docs, hot):
    rows = sorted((r.doc_id, r.text.encode()) for r in docs.collect())
    got = {r.doc_id: tuple(r)[1:] for r in suffix.count_repeats(docs, hot_segments=hot).collect()}
    assert got == slow_repeats(rows, 100)


def test_suffix_runs_and_pieces(spark, monkeypatch):
    """Periodic texts, texts cut into pieces, a hot phrase in varied surroundings."""
    monkeypatch.setattr(suffix, "PIECE", 700)
    rng = random.Random(9)
    word = lambda n: "".join(rng.choice("abcdefgh ") for _ in range(n))
    phrase = word(140)
    texts = ["a" * 900, "ab" * 500, word(1500), *[word(80) + phrase + word(90) for _ in range(40)]]
    texts.append(texts[2][300:900] + "x" + texts[2][100:400])
    frame = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want = slow_repeats([(i, t.encode()) for i, t in enumerate(texts)], 100)
    for hot in (512, 3):
        assert {r.doc_id: tuple(r)[1:] for r in suffix.count_repeats(frame, hot_segments=hot).collect()} == want


def test_suffix_edges(odd, none):
    got = suffix.remove_repeats(odd)
    rows = got.collect()
    assert got.columns[:-1] == odd.columns and len(rows) == len(ODD)
    assert [r for r in rows if r.doc_id == 1][0].text is None and [r for r in rows if r.doc_id == 7][0].text == ODD[-1][1]
    assert {r.label for r in rows} == {"clash"}
    assert suffix.count_repeats(none).count() == 0


# ----------------------------------------------------------------------- 2: PII


def test_surrogates(spark):
    text = "Ask Mrs. Anna Smith or Mr. Smith: Bob@Mail.foo.com, bob@mail.foo.com, +1 (743) 555-3824, +1 743-555-3824, card 4111 1111 1111 1111 not 4111111111111112, 10.2.3.4, 123-45-6789, token = \"2abc3ff2ca8fb1e4c565a0eb63815530a948bdde\", GB82 WEST 1234 5698 7654 32"
    frame = spark.createDataFrame([(1, text, "x"), *ODD], DOCS)
    got = pii.replace(frame)
    assert got.columns == [*frame.columns, "n_entities"] and got.count() == 1 + len(ODD)
    r = got.where("n_entities > 0").first()
    assert r.n_entities == 11 and "4111111111111112" in r.text
    for gone in ("Anna", "Smith", "foo.com", "555-3824", "4111 1111 1111 1111", "10.2.3.4", "123-45-6789", "2abc3ff2", "WEST"):
        assert gone not in r.text
    mails = re.findall(r"\S+@\S+?\.example\.com", r.text)
    assert len(mails) == 2 and mails[0].lower() == mails[1].lower()
    family = re.search(r"Mrs\. (\w+) (\w+) or Mr\. (\w+):", r.text)
    assert family[2] == family[3] != family[1]
    phones = re.findall(r"\+1 [()\d -]{12,14}", r.text)
    assert len({re.sub(r"\D", "", p) for p in phones}) == 1 and len(phones) == 2
    digits = re.search(r"card ((?:\d{4} ){3}\d{4})", r.text)[1].replace(" ", "")
    assert sum(sum(divmod(int(c) * (2 - i % 2), 10)) for i, c in enumerate(digits)) % 10 == 0
    assert {x.doc_id: x.text for x in got.where("n_entities = 0").collect()}[7] == ODD[-1][1]


def test_collisions_are_settled(spark, monkeypatch):
    """Entities whose first surrogates collide by force end up distinct, the same everywhere."""
    real = pii.surrogate

    def poor(kind, form, gender, key, attempt):
        return F.when((kind == "ip") & (attempt == 0), F.lit("240.0.0.1")).otherwise(real(kind, form, gender, key, attempt))

    monkeypatch.setattr(pii, "surrogate", poor)
    frame = spark.createDataFrame([(1, "a 1.2.3.4 b 5.6.7.8 c", "x"), (2, "5.6.7.8", "x"), (3, "9.9.9.9 and 240.0.0.1", "x")], DOCS)
    out = {r.doc_id: re.findall(r"[\d.]{7,}", r.text) for r in pii.replace(frame).collect()}
    assert out[1][1] == out[2][0] and len({*out[1], *out[3]}) == 4 and "240.0.0.1" not in (out[1] + out[3])[3:]


def test_every_given_address_goes(docs):
    pattern = r"[\w.]+@[\w.]+\.com|\+1 \(\d{3}\) \d{3}-\d{4}|\b\d{1,3}(?:\.\d{1,3}){3}\b|\b[0-9a-f]{40}\b"
    left = {r.doc_id: r.text for r in pii.replace(docs).collect()}
    n = 0
    for r in docs.collect():
        for e in re.findall(pattern, r.text):
            n += 1
            assert e not in left[r.doc_id]
        if not re.search(r"[@\d]", r.text):
            assert left[r.doc_id] == r.text
    assert n > 5


def test_long_secrets_and_short_addresses(spark):
    """A secret goes to its last character; addresses with zeros left out go, and all spellings of one are one."""
    rng = random.Random(7)
    word = lambda n: "".join(rng.choice("ABCxyz019-_.") for _ in range(n - 1)) + "q"
    secrets = [word(300), word(5000), "ab12" * 50, "0f" * 2500]
    v6 = ["2001:db8::8a2e:370:7334", "2001:0DB8:0:0:0:8A2E:0370:7334", "fe80::", "::1", "::ffff:192.0.2.128", "::ffff:c000:280", "dead::beef", "1:2:3:4:5:6:7:8"]
    kept = ["std::vector a :: b 12:30:45 1::2::3 x::", "at 10:20 :: end"]
    rows = [(0, f'token = "{secrets[0]}" end', "x"), (1, f"password: {secrets[1]} end", "x"), (2, f"sum {secrets[2]} end", "x"), (3, f"sum {secrets[3]} end", "x")]
    rows += [(10 + i, f"host {a}, end", "x") for i, a in enumerate(v6)] + [(30 + i, t, "x") for i, t in enumerate(kept)]
    out = {r.doc_id: r for r in pii.replace(spark.createDataFrame(rows, DOCS)).collect()}
    for i, s in enumerate(secrets):
        assert out[i].n_entities == 1 and out[i].text.endswith(" end") and not any(s[k : k + 12] in out[i].text for k in range(0, len(s) - 12, 12))
    import ipaddress

    made = [re.fullmatch("host (.*), end", out[10 + i].text)[1] for i in range(len(v6))]
    assert all(out[10 + i].n_entities == 1 and ipaddress.ip_address(m.lower()) not in map(ipaddress.ip_address, v6) for i, m in enumerate(made))
    assert len({ipaddress.ip_address(m.lower()) for m in made}) == 6 == len(set(map(ipaddress.ip_address, v6)))
    assert [out[30 + i].text for i in range(len(kept))] == kept


def test_family_names_stay_apart(spark, monkeypatch):
    """Family names whose first surrogates collide, or are real names, are settled, the same alone and in full names."""
    real = pii._name_part

    def poor(word, given, gender, key, attempt):
        made = real(word, given, gender, key, attempt)
        return made if given else F.when((attempt == 0) & word.isin("smith", "jones"), F.lit("same")).when((attempt == 0) & (word == "brown"), F.lit("stone")).otherwise(made)

    monkeypatch.setattr(pii, "_name_part", poor)
    rows = [(1, "Mr. Smith and Mr. Jones and Mr. Brown", "x"), (2, "Mrs. Anna Smith, Mrs. Anna Jones", "x"), (3, "Mr. Stone", "x"), (4, "Mr. Jones", "x")]
    out = {r.doc_id: [x.split()[-1] for x in re.findall(r"Mrs?\. (\w+(?: \w+)?)(?=,| and|$)", r.text)] for r in pii.replace(spark.createDataFrame(rows, DOCS)).collect()}
    smith, jones, brown = out[1]
    assert len({smith, jones, brown, *out[3]}) == 4 and "Stone" not in (smith, jones, brown)
    assert out[2] == [smith, jones] and out[4] == [jones]


def test_one_name_under_two_titles(spark):
    rows = [(1, "Mrs. Anna Smith met Dr. Anna Smith.", "x"), (2, "Dr. Anna Smith", "x"), (3, "Dr. Otto Smith", "x")]
    out = {r.doc_id: re.findall(r"(?:Mrs|Dr)\. (\w+ \w+)", r.text) for r in pii.replace(spark.createDataFrame(rows, DOCS)).collect()}
    assert out[1][0] == out[1][1] == out[2][0] != out[3][0] and out[1][0].split()[0].endswith(("ria", "lina", "nette", "sea", "dra"))
    assert out[1][0].split()[1] == out[3][0].split()[1]


def test_permutations_are_permutations(spark):
    """Whole small formats map onto themselves, one to one; so do samples of large ones, in their own format."""
    one = [chr(97 + i) for i in range(26)] + [f"{a}{b}" for a in "ab7" for b in "cdefg019"] + [f"{i:03d}" for i in range(1000)]
    frame = spark.createDataFrame([(t,) for t in one], "t string").select("t", pii.permuted(F.col("t"), "k").alias("u"), pii.permuted(F.col("t"), "k", within="phone").alias("p"))
    rows = frame.collect()
    shape = lambda t: re.sub("[a-z]", "a", re.sub("[0-9]", "0", t))
    assert all(shape(r.t) == shape(r.u) for r in rows) and len({r.u for r in rows}) == len({r.p for r in rows}) == len(rows)
    assert {r.u for r in rows if len(r.t) == 3} == {r.t for r in rows if len(r.t) == 3}
    assert all((r.t[0] < "2") == (r.p[0] < "2") for r in rows if r.t[0].isdigit())
    ips = [f"10.{i // 256}.{i % 256}.{i % 7}" for i in range(4000)]
    got = [r.u for r in spark.createDataFrame([(t,) for t in ips], "t string").select(pii.permuted_address(F.col("t"), "k").alias("u")).collect()]
    import ipaddress

    assert len(set(map(ipaddress.ip_address, got))) == len(ips) and len({g.split(".")[0] for g in got}) > 200


def test_full_formats_and_many_names(spark):
    """All 26 one-letter addresses of a domain, secrets without a digit, a column n_entities, and very many family names."""
    rows = [(i, f"write to {chr(97 + i)}@x.com now", "x") for i in range(26)] + [(30, "password: correcthorsebatterystaple end", "x"), (31, "host dead:beef:cafe:babe:dead:beef:cafe:babe up", "x")]
    out = {r.doc_id: r for r in pii.replace(spark.createDataFrame(rows, DOCS).withColumn("n_entities", F.lit("old"))).collect()}
    assert len({out[i].text for i in range(26)}) == 26 and not any("@x.com" in r.text for r in out.values())
    assert "correct" not in out[30].text and out[30].text.endswith(" end") and "beef" not in out[31].text
    assert out[30].n_entities == 1 and list(out[0].asDict()) == ["doc_id", "text", "lang", "n_entities"]
    names = spark.range(100_000).select(F.lit("name").alias("kind"), F.translate(F.col("id").cast("string"), "0123456789", "abcdefghij").alias("form"), F.lit("n").alias("gender"), F.lit(False).alias("mixed"))
    done = pii.settle(names, "k").where("kind = 'family'")
    assert done.count() == 100_000 == done.select("made").distinct().count()


def test_hint_covers_every_pattern(spark):
    texts = ["a@b.co", "token=abcdefghijklmnopqrst", "passwd : abcdefghijklmnopqrst", "api-key:abcdefghijklmnopqrst", "AUTH_KEY=abcdefghijklmnopqrst", "secret = 'abcdefghijklmnopqrst'", "::ffff:abcd", "dead:beef:cafe:babe:dead:beef:cafe:babe"]
    texts += [f"{t} Abc" for t in f"{pii._TITLE_M}|{pii._TITLE_F}|{pii._TITLE_N}".split("|")]
    got = spark.createDataFrame([(t,) for t in texts], "t string").select("t", F.col("t").rlike(pii.ANY).alias("found"), F.col("t").rlike(pii.HINT).alias("hinted")).collect()
    assert all(r.found and r.hinted for r in got), [r for r in got if not (r.found and r.hinted)]


def test_spaces_that_are_full(spark, monkeypatch):
    """Where every surrogate is a real entity too, the job ends, and entities stay distinct."""
    monkeypatch.setattr(pii, "surrogate", lambda kind, form, gender, key, attempt: F.concat(F.lit("9.9.9."), ((F.substring_index(form, ".", -1).cast("int") + 1 + attempt) % 5).cast("string")))
    rows = [(i, f"at 9.9.9.{i} up", "x") for i in range(5)]
    out = [r.text for r in pii.replace(spark.createDataFrame(rows, DOCS)).collect()]
    assert len(set(out)) == 5


# ------------------------------------------------------------------- 4: quality


def slow_base(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    twice = {w for w in windows if windows.count(w) > 1} if len(words) < 3000 else {w for w, k in __import__("collections").Counter(windows).items() if k > 1}
    covered = {j for i, w in enumerate(windows) if w in twice for j in (i, i + 1, i + 2)}
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(covered)


def test_quality(spark, sf, docs):
    labels = common.table(spark, sf, "labels")
    model = quality.train(docs, labels)
    got = {r.doc_id: r for r in quality.score(docs, model).collect()}
    for r in docs.collect():
        assert tuple(got[r.doc_id][b] for b in quality.BASE) == slow_base(r.text)
        assert got[r.doc_id].base_failed == (slow_base(r.text)[0] < 50 or 100 * slow_base(r.text)[4] > 50 * slow_base(r.text)[0])
    kept = quality.keep_good(docs, model)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {k for k, r in got.items() if r.kept}


def test_held_out_accuracy(spark):
    big = "/root/testdata/sf0.1"  # 3,980 labels
    docs, labels = (common.table(spark, big, t) for t in ("documents", "labels"))
    x, y = quality.labelled_sample(docs, labels)
    half = np.arange(len(y)) % 2 == 0
    model = quality.fit(x[half], y[half], tuple(s for _, s in quality.FEATURES))
    assert ((model.score(x[~half]) >= 0.5) == y[~half]).mean() > 0.99


def test_monotone_trees():
    rng = np.random.default_rng(2)
    x = rng.random((2000, 3))
    y = ((x[:, 0] - x[:, 1] + 0.4 * np.sin(9 * x[:, 2]) + 0.3 * rng.standard_normal(2000)) > 0).astype(float)
    model = quality.fit(x, y, (1, -1, 0), trees=40)
    line = np.linspace(0, 1, 50)
    for _ in range(20):
        row = np.tile(rng.random(3), (50, 1))
        up, down = row.copy(), row.copy()
        up[:, 0], down[:, 1] = line, line
        assert (np.diff(model.margin(up)) >= -1e-12).all() and (np.diff(model.margin(down)) <= 1e-12).all()
    assert ((model.score(x) >= 0.5) == y).mean() > 0.75


def test_quality_edges(odd, none):
    model = quality.fit(np.zeros((0, len(quality.FEATURES))), np.zeros(0), tuple(s for _, s in quality.FEATURES))
    got = quality.score(odd, model).collect()
    assert len(got) == len(ODD) and all(not r.kept for r in got if r.base_failed)
    assert quality.score(none, model).count() == 0 and quality.keep_good(odd, model).columns == odd.columns


# ------------------------------------------------------- 5 and 10: shards, buckets


def test_shards(spark, sf, docs):
    got = sharding.assign(docs).toPandas().set_index("doc_id").sort_index()
    sql = sharding.ORACLE_SQL.replace("FROM documents", f"FROM '{sf}/documents.parquet'")
    want = duckdb.sql(sql).df().set_index("doc_id").sort_index()
    for c in ("size", "shard", "slot", "grown_shard"):
        assert (got[c] == want[c]).all()
    moved = got[got.shard != got.grown_shard]
    assert set(moved.grown_shard) <= {24}
    import zlib

    assert all(got.text_crc32[r.doc_id] == zlib.crc32(r.text.encode()) for r in docs.collect())


def test_shard_growth_moves_its_share():
    keys = np.arange(200_000) * 7919
    for n in (1, 5, 24, 100):
        a, b = sharding.jump_hash(keys, n), sharding.jump_hash(keys, n + 1)
        assert set(b[a != b]) == {n} and abs((a != b).mean() - 1 / (n + 1)) < 0.01 and b.max() == n


def test_ranks_over_many_ranges(spark):
    """Sparse ids, nulls, one id of a third of all rows and rows equal in everything; no range holds much more than its share."""
    rows = spark.range(1000).select(F.shiftleft(F.col("id") * 3 - 500, 40).alias("k"), (F.col("id") % 3).alias("g"), F.lit(0).alias("t")).unionByName(spark.sql("select cast(null as bigint) k, 1L g, 0 t from range(5)"))
    rows = common.stored(rows.unionByName(spark.sql("select 77L k, 2L g, 1 t from range(500)")).repartition(7), "rows")
    got = common.gapless_rank(rows, "g", "k", "n", ("t",)).toPandas()
    assert len(got) == 1505
    for _, part in got.groupby("g"):
        part = part.sort_values("n")
        assert part.n.tolist() == list(range(len(part))) and part.k.dropna().is_monotonic_increasing


def test_best_bounds():
    rng = np.random.default_rng(4)
    for _ in range(150):
        n, k = rng.integers(1, 14), int(rng.integers(1, 5))
        lengths, counts = np.sort(rng.choice(60, n, False)) + 1, rng.integers(1, 9, n)
        cuts = [c for r in range(min(k, n)) for c in itertools.combinations(range(1, n), r)]
        best = min(sum(counts[i] * (lengths[next(e for e in [*cut, n] if e > i) - 1] - lengths[i]) for i in range(n)) for cut in cuts)
        bounds, cost = packing.best_bounds(lengths, counts, k)
        assert cost == best == sum(c * (min(b for b in bounds if b >= x) - x) for x, c in zip(lengths, counts, strict=True))


def test_packing_by_given_lengths(spark):
    rows = spark.createDataFrame([(i, "x", n) for i, n in enumerate([3, 3, 5, 9, 9, 20])] + [(9, "x", None)], "doc_id long, text string, n long")
    got = {r.doc_id: (r.n_tokens, r.padded_tokens) for r in packing.pack(rows, buckets=3, multiple=1, length_col="n").collect()}
    assert got == {0: (3, 3), 1: (3, 3), 2: (5, 9), 3: (9, 9), 4: (9, 9), 5: (20, 20), 9: (0, 3)}


def test_packing(docs, odd, none):
    got = packing.pack(docs, budget=2048).toPandas()
    texts = {r.doc_id: r.text for r in docs.collect()}
    assert len(got) == len(texts) and all(len(texts[d].split()) == n for d, n in zip(got.doc_id, got.n_tokens, strict=True))
    for (_, _), batch in got.groupby(["bucket", "batch"]):
        assert len(batch) == 1 or batch.padded_tokens.sum() <= 2048
        assert sorted(batch.place) == list(range(len(batch))) and (batch.n_tokens <= batch.padded_tokens).all()
    assert packing.pack(odd).count() == len(ODD) and packing.pack(none).count() == 0
    assert sharding.assign(odd).count() == len(ODD) and sharding.assign(none).count() == 0


# ------------------------------------------------------------------ 6: pieces


def test_pieces_many_at_a_time():
    """Batches of words agree with the priority queue, word by word, whatever is dropped."""
    model, rng = pieces.load(), random.Random(4)
    merger = pieces.Merger(model)
    for length in (1, 2, 3, 7, 20, 64):
        words = [pieces.MARK + "".join(rng.choice("aeinrst" if i % 2 else "anéßяж漢𝄞7.") for _ in range(length - 1)) for i in range(300)]
        for limit in (0, 1 << 28, 3 << 30):
            keys = pieces.keys_of(3, length, len(words))
            want = [pieces.encode_word(w, model, int(k), limit) for w, k in zip(words, keys, strict=True)]
            ids, sizes, _ = merger.encode(words, keys, limit)
            assert [x.tolist() for x in np.split(ids, np.cumsum(sizes)[:-1])] == want


def slow_pieces(text, model, seed, doc, limit):
    """Every occurrence merged for itself, pair by pair from a plain list."""
    out = []
    words = pieces.Coder._words(None, text) if text else []
    for word, key in zip(words, pieces.keys_of(seed, doc, len(words)).tolist(), strict=True):
        if word == pieces.OWN:
            out += [model.bytes_from[b] for b in pieces.MARK.encode()]
            continue
        cuts, skipped = list(range(len(word) + 1)), set()
        while True:
            pairs = [(-model.scores[word[a:c]], a, b, c) for a, b, c in zip(cuts, cuts[1:], cuts[2:], strict=False) if word[a:c] in model.scores and (a, b, c) not in skipped]
            if not pairs:
                break
            _, a, b, c = min(pairs)
            if pieces._drops(key, a, b, c, limit):
                skipped.add((a, b, c))
            else:
                cuts.remove(b)
        for a, b in itertools.pairwise(cuts):
            out += [model.ids[word[a:b]]] if word[a:b] in model.ids else [model.bytes_from[x] for x in word[a:b].encode()]
    return out


def test_every_occurrence_draws_for_itself(spark):
    """The whole query against plain loops; the share dropped; and how often a word of one merge varies."""
    model = pieces.load()
    texts = ["the thing and then", "a  b\n\nnéw ▁own▁ 𝄞" + "long" * 40, "the " * 400, "", "nation " * 60]
    frame = spark.createDataFrame([*enumerate(texts), (2, texts[2])], "doc_id long, text string")
    for r in pieces.encode(frame, dropout=0.3, seed=9).join(frame.distinct(), "doc_id").collect():
        assert list(r.ids) == slow_pieces(r.text, model, 9, r.doc_id, round(0.3 * 2**32)) and r.lossless
    coder = pieces.Coder(model, 0.1)
    plain = pieces.Coder(model, 0).encode("to").tolist()
    assert len(plain) == 1
    ids = coder.encode("x " + "to " * 20_000).tolist()
    assert 0.75 < ids.count(plain[0]) / 20_000 < 0.91
    drops = pieces.dropped(pieces.keys_of(1, 5, 200_000), np.full(200_000, 77, np.uint64), coder.limit).mean()
    assert abs(drops - 0.1) < 0.004


def test_pieces_in_groups(monkeypatch):
    """Groups of texts, and a memory that starts anew, change no result."""
    model, texts = pieces.load(), [f"word{i % 7} some{i} text" for i in range(50)]
    want = [x.tolist() for x in pieces.Coder(model).encode_all(texts, list(range(50)))]
    monkeypatch.setattr(pieces, "REMEMBERED", 3)
    coder = pieces.Coder(model)
    assert [coder.encode(t, i).tolist() for i, t in enumerate(texts)] == want
    assert pieces.together(["abc", None, "d" * 9, "e", "f"], 4) == [(0, 2), (2, 3), (3, 5)] and pieces.together([]) == [(0, 0)]


def test_pieces(docs, odd, none):
    import sentencepiece

    model, lib = pieces.load(), sentencepiece.SentencePieceProcessor(model_file=pieces.MODEL)
    plain, first, again, other = pieces.Coder(model, 0), pieces.Coder(model, 0.2, 1), pieces.Coder(model, 0.2, 1), pieces.Coder(model, 0.2, 2)
    texts = ["", " ", "a  b", "\n\n x", "▁a▁ b▁", "\n\0\n▁", "𝄞é", "x" * 500] + [r.text for r in docs.limit(60).collect()]
    varied = 0
    for i, t in enumerate(texts):
        if pieces.MARK not in t:
            assert plain.encode(t).tolist() == lib.encode(t)
        a = first.encode(t, i).tolist()
        assert a == again.encode(t, i).tolist() and pieces.decode(a, model) == t == pieces.decode(other.encode(t, i), model)
        varied += a != other.encode(t, i).tolist()
    assert varied > 40
    rows = pieces.encode(odd)
    assert rows.where("lossless").count() == len(ODD)
    back = {(r.doc_id, r.text) for r in pieces.decode_rows(rows).collect()}
    assert back == {(d, t) for d, t, _ in ODD}
    assert pieces.encode(none).count() == 0


# -------------------------------------------------------------------- 7: html


PAGE = '<html><head><title>T</title><style>p{{}}</style><script>var a="</p>";</script></head><body><header>Top</header><nav><ul><li>a<li>b</ul></nav><!-- ad --><div class="cookie-notice">We use</div><div class="ad">buy</div><article><h1>Head {0} &amp; x</h1><p>One <b>two</b>three<br>four {0}<p>five  &eacute;\n six<form><input><button>go</button></form><div class="comments"><p>bad</p></div></article><aside>s</aside><footer>&copy; f</footer></body></html>'


def test_main_text(spark, sf):
    pages = [(i, f"http://h{i % 2}.org/{i}", PAGE.format(i)) for i in range(9)] + [(20, None, None), (21, "http://x.org/", ""), (22, "nonsense", "just text &lt;"), (23, "http://y.org", "<p>open <b>tags")]
    got = {r.page_id: r for r in html.main_text(spark.createDataFrame(pages, "page_id long, url string, html string").withColumn("host", F.lit(1))).collect()}
    assert len(got) == len(pages)
    for i in range(9):
        assert got[i].text == f"Head {i} & x\n\nOne twothree four {i}\n\nfive é six" and got[i].n_chars == len(got[i].text)
    assert (got[20].text, got[21].text, got[22].text, got[23].text) == ("", "", "just text <", "open tags")
    import html as entities

    given = common.table(spark, sf, "pages")
    texts = {r.page_id: r.text for r in html.main_text(given).collect()}
    assert texts == {r.page_id: r.text for r in html.main_text(given, broadcast_hosts=0).collect()}
    for r in given.collect():
        inner = r.html[r.html.index("<article>") + 9 : r.html.index("</article>")]
        blocks = [re.sub(r"\s+", " ", entities.unescape(re.sub(r"</?b>", "", b.replace("<br>", " ")))).strip() for b in re.split(r"</?(?:p|h1)>", inner)]
        assert texts[r.page_id] == "\n\n".join(b for b in blocks if b)


def test_nested_and_divided_articles(spark):
    """Headline and lead above a deeper body stay, and so do all sections of an article, with or without <article>."""
    body = "long text of the page " * 9
    inner = {
        "nested": "<article><h1>Head {0}</h1><p>lead {0}</p><div class=body><p>" + body + "{0}</p></div></article>",
        "parts": "<article><section class=a><p>" + body + "{0}</p></section><section class=b><p>rest {0}</p></section></article>",
        "plain": "<div class=c1><h1>Head {0}</h1><div class=c2><p>" + body + "{0}</p></div></div>",
        "two": "<article class=x><p>" + body + "{0}</p></article><article class=y><p>more {0}</p></article>",
    }
    pages = [(10 * k + i, f"http://{h}.org/{i}", f"<html><body><nav>menu</nav>{x.format(i)}<footer>f</footer></body></html>") for k, (h, x) in enumerate(inner.items()) for i in range(4)]
    pages.append((99, "http://nested.org/x", "<html><body><article><p>" + body + "</p></article><article><p>second</p></article></body></html>"))
    got = {r.page_id: r.text.split("\n\n") for r in html.main_text(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    for i in range(4):
        assert got[i] == [f"Head {i}", f"lead {i}", f"{body}{i}"]
        assert got[10 + i] == [f"{body}{i}", f"rest {i}"]
        assert got[20 + i] == [f"Head {i}", f"{body}{i}"]
        assert got[30 + i] == [f"{body}{i}", f"more {i}"]
    assert got[99] == [body.strip(), "second"]


def frame(i, n, host="news.org"):
    """A page of generated slots in a template whose element names and classes say nothing, and its article."""
    rng = random.Random(i)
    text = lambda k: " ".join(f"w{rng.randrange(10**6)}" for _ in range(k))
    blocks = [text(6), *[text(rng.randrange(9, 30)) for _ in range(n)]]
    menu = "".join(f"<div><a href=/{j}>{text(2)}</a></div>" for j in range(rng.randrange(2, 6)))
    main = f"<div class=c1><h1>{blocks[0]}</h1>" + "".join(f"<div class=c2><p>{b}</div>" for b in blocks[1:]) + "<div class=c17>Read more on our site</div></div>"
    return f"<html><body><div class=c0><div>Our site since 1999</div>{menu}</div>{main}<div class=c9>All rights kept</div></body></html>", blocks


def test_template_of_a_host(spark):
    """Text that all pages of a host share in the frame goes; what differs in the article stays, whatever the names say. Copies add nothing."""
    made = {i: frame(i, 1 + i % 5) for i in range(24)}
    rows = [(i, f"http://news.org/{i}", h) for i, (h, _) in made.items()] + [(100 + i, "http://news.org/again", made[3][0]) for i in range(30)]
    one = frame(77, 3)
    rows += [(500, "http://alone.org/", one[0])]
    got = {r.page_id: r.text for r in html.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert len(got) == len(rows)
    for i, (_, blocks) in made.items():
        assert got[i] == "\n\n".join(blocks)
    assert all(got[100 + i] == got[3] for i in range(30))
    assert all(b in got[500] for b in one[1])  # a host of one page has no template, and loses nothing


def test_copies_of_an_article_keep_it(spark):
    rows = [(i, f"http://c.org/{i}", f"<body><nav>m{i}</nav><article><h1>Same</h1><p>{'same text ' * 20}</article><footer>{i}</footer></body>") for i in range(12)]
    got = html.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert {r.text for r in got} == {"Same\n\n" + ("same text " * 20).strip()}
    rows = [(i, f"http://d.org/{i}", f"<body><nav>m</nav><div><h1>Same</h1><p>{'same text ' * 20}</p><p>{i}</p></div><footer>{i}</footer></body>") for i in range(12)]
    got = html.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert {r.text for r in got} == {f"Same\n\n{('same text ' * 20).strip()}\n\n{i}" for i in range(12)}


def test_vectors_and_validity():
    """Classes against occurrence vectors built in full; classes out of order or overlapping are no template."""
    docs = [html.Page(f"<body><div class=a>x</div>{'<p>y</p>' * k}<div class=b>z{k}</div></body>") for k in range(1, 5)]
    full: dict[int, list[int]] = {}
    for d, page in enumerate(docs):
        for p, n in enumerate(page.count):
            full.setdefault(page.token[p], [0] * len(docs))[d] = n
    assert sorted(map(tuple, full.values())) == sorted([(1, 1, 1, 1)] * 4 + [(1, 2, 3, 4)])
    a, b = (html.Page(f"<body>{x}</body>") for x in ("<div class=a></div><div class=b></div>", "<div class=b></div><div class=a></div>"))
    classes = {t: 7 for t in a.token[2:]}
    assert html.walk(a, [], classes, {7: 2})[7][2] and html.walk(a, [], classes, {7: 2})[7][0] != html.walk(b, [], classes, {7: 2})[7][0]
    lap = html.Page("<body><div class=a></div><div class=b></div><div class=c></div><div class=d></div></body>")
    t = lap.token[2:]
    crossed = html.walk(lap, [], {t[0]: 1, t[2]: 1, t[1]: 2, t[3]: 2}, {1: 2, 2: 2})
    assert crossed[1][2] and not crossed[2][2]
    nested = html.walk(lap, [], {t[0]: 1, t[3]: 1, t[1]: 2, t[2]: 2}, {1: 2, 2: 2})
    assert nested[1][2] and nested[2][2] and nested[1][1] != nested[2][1]


def test_hostile_pages_and_names():
    alone = html.Template(None)
    start = time.perf_counter()
    deep = html.extract_text("<div>" * 5000 + "".join(f"<p>a{i}</p></b>" for i in range(500)), alone)
    assert deep == "\n\n".join(f"a{i}" for i in range(500))
    assert len(html.extract_text('<a "x ' * 170_000, alone)) > 1_000_000 and html.extract_text("<p>a" + "<script>" * 100_000, alone) == "a"
    assert time.perf_counter() - start < 20
    page = '<article>One <span class="ad">buy <span>y</span> z</span> two <script>x</script>three<p class="ad-hoc">q<p class=related-work>r <math>m</math><p class=ad>gone<header>h</header><footer>f</footer></article>'
    assert html.extract_text(page, alone) == "One two three\n\nq\n\nr m\n\nh"
    assert html.extract_text("<body><div class=no-sidebar><p>kept<div id=comments>c</div></div></body>", alone) == "kept"
    assert html.extract_text("<main><div class=intro>i</div><div class=body>b</div></main>", alone) == "i\n\nb"


def test_pages_edges(spark):
    assert html.main_text(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0
    rows = [(1, "http://a.org/", "<p>same</p>", 5)] * 3 + [(None, None, None, 5), (2, "http://a.org/", "<p>same</p>", None)]
    got = html.main_text(spark.createDataFrame(rows, "page_id long, url string, html string, text long")).collect()
    assert sorted((r.page_id or 0, r.text, r.n_chars) for r in got) == [(0, "", 0), *[(1, "same", 4)] * 3, (2, "same", 4)]


# -------------------------------------------------------------------- 8: WARC


def test_archives(spark, sf, tmp_path):
    pages = common.table(spark, sf, "pages").unionByName(spark.createDataFrame([(900, "u", None), (901, None, ""), (902, "http://a", "same"), (903, "http://b", "same"), (903, "http://b", "same")], "page_id long, url string, html string"))
    got = warc.round_trip(pages).collect()
    bodies = {r.page_id: (r.html or "").encode() for r in pages.collect()}
    assert len(got) == pages.count()
    firsts: dict[bytes, int] = {}
    for k in sorted(bodies):
        firsts.setdefault(bodies[k], k)
    for r in got:
        first = firsts[bodies[r.page_id]]
        assert r.payload_bytes == len(bodies[r.page_id]) and r.payload_digest == warc.payload_digest(bodies[r.page_id])
        assert (r.record_type, r.refers_to) == (("response", None) if first == r.page_id else ("revisit", first))
    archives = warc.write_archives(warc.plan_records(pages), archive_bytes=1 << 16)
    assert warc.export_files(archives, str(tmp_path)) > 1
    back = warc.read_files(spark, f"file://{tmp_path}").where("record_type = 'response'").collect()
    assert all(bytes(r.payload) == bodies[r.page_id] for r in back)


def test_broken_archives():
    record = warc.build_record([("WARC-Type", "response"), ("WARC-Record-ID", "<urn:x>"), ("WARC-Date", "2024-01-01T00:00:00Z")], warc.http_response(b"hello"))
    data = warc.build_archive([record] * 3)
    assert [b for _, b in warc.read_archive(data)] == [warc.http_response(b"hello")] * 3
    for bad in (data[:-3], data[:9], data[:4] + b"\xff\xff\xff\x7f" + data[8:], data + b"junk"):
        with pytest.raises(Exception):
            list(warc.read_archive(bad))
    size = b"Content-Length: %d" % len(warc.http_response(b"hello"))
    assert record.count(size) == 1
    for raw in (record.replace(b"WARC/1.1", b"HTTP/1.1"), record.replace(size, size + b"0"), record[:-2], record.replace(b"WARC-Date", b"X-Date")):
        with pytest.raises(warc.InvalidRecord):
            warc.parse_record(raw)


def test_rejected_archives(spark):
    """One broken archive costs what stands behind the fault in it, and is named; the others are read whole."""
    name = lambda i: ("WARC-Record-ID", f"<urn:x:{i}>")
    records = [warc.build_record([("WARC-Type", "response"), name(i), ("WARC-Date", "2024-01-01T00:00:00Z"), ("X-Page-ID", str(i))], warc.http_response(b"x%d" % i)) for i in range(3)]
    good, cut = warc.build_archive(records), warc.build_archive(records)[:-5]
    frame = spark.createDataFrame([("good", good), ("cut", cut), ("noise", b"noise"), ("none", None)], "archive string, data binary")
    assert sorted((r.archive, r.page_id) for r in warc.read_archives(frame, strict=False).collect()) == [("cut", 0), ("cut", 1), ("good", 0), ("good", 1), ("good", 2)]
    assert {(r.archive, r.n_read) for r in warc.rejected(frame).collect()} == {("cut", 2), ("noise", 0)}
    with pytest.raises(Exception):  # noqa: B017
        warc.read_archives(frame).count()


# --------------------------------------------------------------- 9: embeddings


def test_bounds_hold():
    rng = np.random.default_rng(6)
    for scale in (1.0, 1e-30, 1e30):
        x = rng.standard_normal((60, 48)) * scale
        x[30:] = x[:30] + rng.standard_normal((30, 48)) * scale * rng.uniform(0.02, 0.4, (30, 1))
        i, j, n = embed.tile_links(x, x, 0.98, True)
        u = x / np.linalg.norm(x, axis=1, keepdims=True)
        want = {(a, b) for a, b in zip(*np.nonzero(u @ u.T >= 0.98), strict=True) if a < b}
        assert set(zip(i.tolist(), j.tolist(), strict=True)) == want and n < 60 * 59 / 2
    for dim in (3072, 5000):  # integer products beyond what float32 holds
        x = np.abs(rng.standard_normal((20, dim)))
        x[10:] = x[:10] * (1 + 0.15 * rng.standard_normal((10, dim)))
        codes = embed.unit_codes(x)
        middle, error = embed.estimates(codes, codes)
        q, scale = codes[0].astype(np.int64), codes[1]
        assert np.array_equal(middle, (q @ q.T).astype(float) * scale[:, None] * scale[None, :])
        u = x / np.linalg.norm(x, axis=1, keepdims=True)
        assert (np.abs(u @ u.T - middle) <= error + 1e-12).all()


def test_embeddings(spark):
    rng = np.random.default_rng(7)
    base = rng.standard_normal((40, 16))
    rows = [(k, (base[k % 40] + 0.09 * rng.standard_normal(16) * (k >= 40)).tolist(), int(k % 3)) for k in range(200)]
    rows += [(300 + k, rows[k][1], rows[k][2]) for k in range(10)]
    rows += [(400, None, 1), (401, [0.0] * 16, 1), (402, [float("nan")] * 16, 1), (403, [None] + [1.0] * 15, 1), (404, rows[0][1], None), (405, [], 1), (406, [1.0, 2.0], 1)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").withColumn("key", F.lit(1))
    got = {r.vec_id: r for r in embed.near_duplicates(frame, block=32).collect()}
    live = [r for r in rows if r[0] < 400]
    near = {a[0]: {b[0] for b in live if b[0] != a[0] and a[2] == b[2] and embed.cosine(np.array([a[1]]), np.array([b[1]]))[0] >= 0.98} for a in live}
    root = {k: k for k in near}
    while True:
        new = {k: min([root[k], *[root[b] for b in near[k]]]) for k in near}
        if new == root:
            break
        root = new
    for k in near:
        assert (got[k].n_links, got[k].component_id, got[k].kept) == (len(near[k]), root[k], root[k] == k)
    assert all((got[k].n_links, got[k].component_id) == (0, k) for k in range(400, 407)) and len(got) == len(rows)
    assert sum(map(len, near.values())) > 50
    assert embed.near_duplicates(frame.where("vec_id < 0")).count() == 0


# ---------------------------------------------------------------- shared parts


def test_components(spark):
    rng = random.Random(8)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(k, k + 1) for k in range(1000, 1200)] + [(7000, 7000)]
    got = {r.id: r.root for r in common.connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    nodes, roots = common.local_components(*map(np.array, zip(*edges, strict=True)))
    assert got == dict(zip(nodes.tolist(), roots.tolist(), strict=True))


def test_only_the_entry_reads_this_package():
    import pathlib

    root = pathlib.Path(__file__).parents[2]
    for path in (root / "netprop").rglob("*.py"):
        if "llm" not in path.parts:
            assert "netprop.llm" not in path.read_text()
