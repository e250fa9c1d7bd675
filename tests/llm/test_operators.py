"""Each operator on one small table of hard rows, against brute force."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter
from functools import partial

import numpy as np
import pytest
import xxhash

tokenizers = pytest.importorskip("tokenizers")
public_tokenizers = pytest.importorskip("public_tokenizers")

from doccurate.llm import decontaminate, multiset, packing, pii, simhash, substring_dedup, token_counts, token_store, toxicity, url_filter  # noqa: E402

WORDS = ["alpha", "Beta", "gämma", "delta.", "ep-silon", "the", "of", "12", "été", "ß", "x"]
SCHEMA = "doc_id long, text string, score double, fp string, n_words int, row int, view string"


def _texts():
    rng = random.Random(4)
    say = lambda n: " ".join(rng.choice(WORDS) for _ in range(n))
    shared, long = say(60), say(6000)
    return [
        None, "", " \n\t ", "one", "three short words", shared, shared, f"{say(20)} {shared} {say(9)}", f"{say(7)}\n{shared[:200]}", long,
        "the " * 90, "a b " * 60, "日本 <|endoftext|> 😀 x  y\r\n z", "mail a.b@c.de or 10.0.0.1 and 4111 1111 1111 1111, +1 (269) 555-3296 4524132264652876",
        f"{say(30)} {shared}", say(50), "x" * 5000, "Repeated line\nRepeated line\n\nRepeated line",
    ]


@pytest.fixture(scope="module")
def rows():
    out = [(k * 3 + 1, t) for k, t in enumerate(_texts())]
    return [*out, out[5], (None, "no id here"), (-7, "below zero")]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame([(k, t, 0.5, "f", 1, 2, "v") for k, t in rows], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def as_set(df, *columns):
    return sorted(map(repr, (tuple(r) for r in df.select(*columns).collect())))


def test_substring_dedup(spark, docs, rows):
    all_words = [words(t) for _, t in rows]
    seen = Counter(tuple(w[k : k + 35]) for w in all_words for k in range(len(w) - 34))
    expected = []
    for (key, _), w in zip(rows, all_words, strict=True):
        gone = [False] * len(w)
        for k in range(len(w) - 34):
            if seen[tuple(w[k : k + 35])] > 1:
                gone[k : k + 35] = [True] * 35
        kept = " ".join(x for x, g in zip(w, gone, strict=True) if not g)
        expected.append((key, len(w), sum(gone), hashlib.sha256(kept.encode()).hexdigest()))
    found = substring_dedup.repeated_words(spark, docs)
    assert as_set(found, "doc_id", "n_words", "n_removed", "kept_sha256") == sorted(map(repr, expected))
    assert sum(e[2] for e in expected) > 200


def test_substring_dedup_random_windows(spark):
    rng = random.Random(8)
    texts = [" ".join(rng.choice("ab c d e".split()) if rng.random() < 0.5 else "a" for _ in range(rng.randint(0, 160))) for _ in range(60)]
    texts += [t[rng.randint(0, 40) :] for t in texts[:20]]
    unit = substring_dedup.Unit([t.encode() for t in texts], 35)
    chosen, _ = unit.anchors()
    by_window = {}
    for p, c in zip(unit.valid.tolist(), chosen.tolist(), strict=True):
        if c >= 0:  # equal windows choose the same place
            assert by_window.setdefault(unit.names[p : p + 35].tobytes(), c - p) == c - p


def plain_fingerprint(text):
    """Bits that more than half of the shingles' XXH64 values have, counted one by one."""
    words = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: bytes([m[0][0] + 32]), (text or "").encode()))
    shingles = [b" ".join(words[k : k + 4]) for k in range(max(len(words) - 3, 1))] if words else []
    hashes = [xxhash.xxh64(x, seed=42).intdigest() for x in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_simhash(spark, docs, rows):
    fps = [plain_fingerprint(t) for _, t in rows]
    assert fps == [simhash.fingerprint((t or "").encode()) for _, t in rows]
    component = {}
    for i in range(len(fps)):
        reach, todo = {i}, [i]
        while todo:
            x = todo.pop()
            for j in range(len(fps)):
                if j not in reach and (fps[x] ^ fps[j]).bit_count() <= 4:
                    reach.add(j)
                    todo.append(j)
        component[i] = min((rows[j][0] for j in reach if rows[j][0] is not None), default=None)
    expected = sorted(repr((rows[i][0], fps[i] - (1 << 64) * (fps[i] >> 63), component[i])) for i in range(len(rows)))
    assert as_set(simhash.near_duplicates(spark, docs), "doc_id", "fp", "component_id") == expected


def test_simhash_finds_all_links_in_hot_shards(spark, monkeypatch):
    monkeypatch.setattr(simhash, "HOT", 8)
    rng = np.random.default_rng(0)
    base = rng.integers(0, 1 << 62, 6)
    fps = [int(b) ^ sum(1 << int(x) for x in rng.choice(64, rng.integers(0, 4), replace=False)) for b in base for _ in range(60)]
    nodes = spark.createDataFrame([(f - (1 << 64) * (f >> 63),) for f in set(fps)], "fp long")
    pairs = simhash.links(spark, nodes)
    found = {r.node: r.root for r in simhash.components(spark, pairs).collect()}
    own = sorted({f - (1 << 64) * (f >> 63) for f in fps})
    arr = np.array(own, np.int64).view(np.uint64)
    near = np.bitwise_count(arr[:, None] ^ arr[None]) <= 4
    label = list(range(len(own)))
    for _ in range(len(own)):
        new = [min(label[j] for j in np.flatnonzero(near[i])) for i in range(len(own))]
        if new == label:
            break
        label = new
    assert [found.get(x, x) for x in own] == [own[k] for k in label]


def test_decontamination(spark, docs, rows):
    shared = _texts()[5]
    bench = [(1, " ".join(shared.split()[5:25])), (2, "three SHORT words"), (3, None), (4, "..."), (5, "never in any of the documents at all, is it or not")]
    items = spark.createDataFrame(bench, "item_id long, text string")
    fold = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    windows = [(i, tuple(w[k : k + 10])) for i, t in bench if (w := fold(t)) for k in range(max(len(w) - 9, 1))]
    expected = []
    for key, text in rows:
        w, hit, got = fold(text), set(), set()
        for item, p in windows:
            for k in range(len(w) - len(p) + 1):
                if tuple(w[k : k + len(p)]) == p:
                    hit |= set(range(k, k + len(p)))
                    got.add(item)
        expected.append((key, len(w), len(hit), sorted(map(str, got))))
    for size in (decontaminate.BLOCK_BYTES, 60):  # one block, and several
        found = decontaminate.find_contamination(spark, docs, items, block_bytes=size).collect()
        assert sorted(repr((r.doc_id, r.n_words, sum(b - a for a, b in r.runs), list(r["items"]))) for r in found) == sorted(map(repr, expected))
    assert sum(e[2] for e in expected) > 50
    left = {r.doc_id: r.text for r in decontaminate.cleaned(spark, docs, items).collect()}
    assert shared[40:100] not in left[22] and left[4] == ""
    assert decontaminate.remove_spans("Keep, this one. Cut me! End", [[3, 5]]) == "Keep, this one. ! End"


def test_token_counts_and_store(spark, docs, rows, tmp_path):
    lib = tokenizers.Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    counted = token_counts.count_tokens(docs, public_tokenizers.path("word_bpe_49k.json"))
    expected = [(k, len((t or "").encode()), n := len(lib.encode(t or "", add_special_tokens=False).ids), n > 2048) for k, t in rows]
    assert as_set(counted, "doc_id", "n_bytes", "n_tokens", "over_limit") == sorted(map(repr, expected))

    lib = tokenizers.Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    manifest = token_store.write_store(spark, docs, public_tokenizers.path("byte_bpe_50k.json"), str(tmp_path), 2)
    back = token_store.read_store(spark, str(tmp_path), manifest).collect()
    order = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or ""))
    start, expected = 0, []
    for key, text in order:
        ids = [*lib.encode(text or "", add_special_tokens=False).ids, 2]
        expected.append((key, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    assert sorted(map(repr, (tuple(r) for r in back))) == sorted(map(repr, expected))
    assert [len(x) for x in token_store.lookup(str(tmp_path), manifest, 16)] == [e[2] for e in expected if e[0] == 16]
    assert token_store.lookup(str(tmp_path), manifest, 17) == []


def test_perfect_hash_is_minimal():
    keys = np.unique(np.random.default_rng(1).integers(0, 1 << 63, 5000)).astype(np.uint64)
    assert sorted(token_store.PerfectHash.build(keys).slots(keys).tolist()) == list(range(len(keys)))


def test_packing(spark, docs, rows):
    lib = tokenizers.Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    found = packing.pack(spark, docs, public_tokenizers.path("word_bpe_49k.json"), capacity=256).collect()
    expected = []
    for key, text in rows:
        ids = [*lib.encode(text or "", add_special_tokens=False).ids, 0]
        expected += [(key, k, s, len(p := ids[s : s + 256]), zlib.crc32(np.array(p, "<u4").tobytes())) for k, s in enumerate(range(0, len(ids), 256))]
    assert sorted(repr(tuple(r)[:5]) for r in found) == sorted(map(repr, expected))
    bins = {}
    for r in found:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in bins.values():
        parts.sort()
        assert [o for o, _ in parts] == [sum(n for _, n in parts[:k]) for k in range(len(parts))] and sum(n for _, n in parts) <= 256
    assert len(bins) <= -(-sum(r.length for r in found) // 256) + 1


@pytest.mark.parametrize("size", [0, 1, 900, 10**9])
def test_packing_plan(size):
    rng = np.random.default_rng(size % 97)
    share = rng.exponential(1, 511)
    counts = {k + 1: int(n) for k, n in enumerate(rng.multinomial(size, share / share.sum())) if n}
    plan = packing.plan(counts, 512)
    got = Counter()
    for parts, times in zip(plan.parts, plan.times, strict=True):
        assert sum(k * n for k, n in parts.items()) <= 512
        for length, copies in parts.items():
            got[length] += copies * times
    assert got == counts
    # A bound that counts pieces over half a sequence too: two of them never share one.
    bound = 0
    for least in range(257):
        big = sum(n for k, n in counts.items() if k > 512 - least)
        middle = {k: n for k, n in counts.items() if 256 < k <= 512 - least}
        room = sum((512 - k) * n for k, n in middle.items())
        small = sum(k * n for k, n in counts.items() if least <= k <= 256)
        bound = max(bound, big + sum(middle.values()) + max(0, -(-(small - room) // 512)))
    assert plan.sequences <= bound * 1.01 + 2


def test_fingerprints(spark, docs, rows):
    found = multiset.with_edits(spark, docs).collect()
    order = sorted(rows, key=lambda r: (r[0] is None, -(r[0] or 0), r[1] or ""))
    expected = []
    for k, (key, text) in enumerate(order):
        text, after = text or "", order[(k + 1) % len(order)][1] or ""
        half = len(text) // 2
        edited = text[: len(text) - half] + after[:half]
        expected.append((key, len(text), hashlib.sha256(edited.encode()).hexdigest()))
    assert sorted(repr(tuple(r)[:3]) for r in found) == sorted(map(repr, expected))
    by_id = {r.doc_id: r for r in found}
    assert by_id[16].fingerprint == by_id[19].fingerprint != by_id[22].fingerprint
    assert all(0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1 for r in found)


def test_fingerprints_add_up(spark):
    parts = spark.createDataFrame([(1, "b line here\na line"), (1, "c"), (2, "a line\nc\nb line here"), (3, "a line")], "k int, text string")
    r = {x.k: x for x in multiset.fingerprints(parts, "k").collect()}
    assert r[1].wide == r[2].wide and r[1].narrow == r[2].narrow and r[1].wide != r[3].wide
    wide = spark.createDataFrame([(r[2].wide, r[3].wide)], "a array<long>, b array<long>")
    less = wide.select(multiset.combine(wide.a, wide.b, 32, -1).alias("x")).first().x
    rest = multiset.fingerprints(spark.createDataFrame([(1, "c\nb line here")], "k int, text string"), "k").first()
    assert less == rest.wide


def test_pii(docs):
    patterns = {
        "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
        "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    }
    rng = random.Random(3)
    bits = ["a", "b.", "@", "@", "x@y.z", ".", "-", "1", "12", "4111111111111111", " ", "+4", "é", "(", ")", "255", "1.1.1.1"]
    for _ in range(20000):
        text, expected = "".join(rng.choice(bits) for _ in range(rng.randint(1, 14))), []
        for kind, pattern in patterns.items():
            for m in re.finditer(pattern, text):
                d = re.sub("[^0-9]", "", m[0])
                good = {"email": True, "ip": kind == "ip" and all(int(x) <= 255 for x in m[0].split(".")), "card": 14 <= len(d) <= 19 and pii.luhn(d), "phone": 10 <= len(d) <= 15}[kind]
                expected += [(*m.span(), kind)] * good
        assert sorted(pii.base_spans(text)) == sorted(expected), text
    assert pii.mod97("GB82WEST12345698765432") and not pii.mod97("GB82WEST12345698765431")
    spans = {r.doc_id: [(s.kind, s.start, s.end) for s in r.spans] for r in pii.spans_of(docs).collect()}
    assert [k for k, *_ in spans[40]] == ["email", "ip", "card", "phone", "card"] and spans[1] == []
    kept = {r.doc_id: r.text for r in pii.redacted(docs).collect()}
    assert "[EMAIL]" in kept[40] and "4524132264652876" not in kept[40] and kept[1] is None and kept[10] == "one"


def test_toxicity(spark, docs):
    rng = random.Random(1)
    rows = [(k, " ".join(rng.choice(WORDS) for _ in range(40)) + (" idiot moron" if k % 5 == 0 else ""), k % 5 == 0) for k in range(1200)]
    table = spark.createDataFrame([(k, t) for k, t, _ in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(k, int(y)) for k, _, y in rows] + [(10**6, 1), (5, None)], "doc_id long, toxic int")
    model = toxicity.train(spark, table, labels.filter("doc_id % 4 <> 0"))
    score = {r.doc_id: r.score for r in toxicity.scored(table, model).collect()}
    held = [(score[k], y) for k, _, y in rows if k % 4 == 0]
    assert all((s >= 0.3) == y for s, y in held)
    assert len(model.at) < 3000
    plain = toxicity.scored(docs.select("doc_id", "text"), model).filter("text is null or text = ''").collect()
    assert len({r.score for r in plain}) == 1 and plain[0].score < 0.3
    none = toxicity.train(spark, table, labels.limit(0))
    assert {r.score for r in toxicity.scored(table, none).limit(3).collect()} == {0.5}


def test_url_filter(spark):
    rng = random.Random(2)
    urls = [None, "", "no scheme", "http://", "HTTP://EXAMPLE.ORG/es/x?q#f", "http://a.example.org/en/12", "http://org/x", "http://notorg/x", "ftp://x.com/de/?a", "http://x.com/fr/1", "http://example.org:80/es/"]
    urls += [f"https://h{rng.randint(0, 9)}.example.{rng.choice(['org', 'com', 'net'])}/{rng.choice(['en', 'es', 'fr', 'de'])}/{rng.randint(0, 999)}" for _ in range(600)]
    pages = spark.createDataFrame([(k, u, 1) for k, u in enumerate(urls)], "page_id long, url string, score int")
    found = {r.page_id: r for r in url_filter.judge(spark, pages).collect()}
    for k, u in enumerate(urls):
        rest = u.split("://", 1)[1] if u and "://" in u else ""
        host = re.match("[^/?#]*", rest)[0].lower()
        path = re.match("[^?#]*", rest[len(host) :])[0]
        fits = [(len(h + p), h + p, v) for h, p, v in url_filter.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        r = found[k]
        assert (r.host, r.path, r.rule) == (host, path, max(fits)[1] if fits else None)
        assert r.verdict in ("allow", "block") and (not fits or r.verdict == max(fits)[2])
    net = [found[k] for k, u in enumerate(urls) if u and "example.net/" in u]
    good = [r.verdict == ("block" if "/de/" in r.path else "allow") for r in net if "/fr/" in r.path or "/de/" in r.path]
    assert sum(good) / len(good) > 0.8


def brute_chance(counts, alphabet, context, char):
    below = brute_chance(counts, alphabet, context[1:], char) if context else 1 / alphabet
    seen = counts.get(context, {})
    return (seen.get(char, 0) + len(seen) * below) / (sum(seen.values()) + len(seen)) if seen else below


@pytest.mark.parametrize("frequent", [30, 20_000])
def test_url_scores_against_brute_force(spark, frequent):
    rng = random.Random(4)
    urls = [(f"http://{rng.choice(['ab', 'cé', '𝒳y'])}.org/{rng.choice(['en', 'de'])}/{rng.randint(0, 40)}", rng.randint(0, 3), rng.randint(0, 2)) for _ in range(60)]
    urls = list({u: (u, a, b) for u, a, b in urls}.values()) + [("x://" + "z" * 3000, 0, 0), ("://", 1, 0)]
    order, models, chars = 3, [{}, {}], set()
    for url, *times in urls:
        text = "\x02" * order + url + "\x03"
        for model, n in zip(models, times, strict=True):
            for k in range(order, len(text) if n else 0):
                chars.add(text[k])
                for size in range(order + 1):
                    nexts = model.setdefault(text[k - size : k], {})
                    nexts[text[k]] = nexts.get(text[k], 0) + n
    rows = spark.createDataFrame(urls, "url string, accepted long, rejected long")
    found = {r.url: r.score for r in url_filter.scored(spark, rows, order, frequent).collect()}
    assert len(found) == len(urls)
    for url, *_ in urls:
        text = "\x02" * order + url + "\x03"
        logs = [sum(math.log(brute_chance(m, len(chars) + 1, text[k - order : k], text[k])) for k in range(order, len(text))) for m in models]
        assert abs(found[url] - (logs[0] - logs[1]) / (len(url) + 1)) < 1e-6


def test_empty_tables(spark, empty):
    items = spark.createDataFrame([], "item_id long, text string")
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    vocabulary = public_tokenizers.path("word_bpe_49k.json")
    assert substring_dedup.repeated_words(spark, empty).count() == 0
    assert simhash.near_duplicates(spark, empty).count() == 0
    assert simhash.one_of_each(spark, empty).count() == 0
    assert decontaminate.find_contamination(spark, empty, items).count() == 0
    assert token_counts.count_tokens(empty, vocabulary).count() == 0
    assert packing.pack(spark, empty, vocabulary).count() == 0
    assert multiset.with_edits(spark, empty).count() == 0
    assert pii.spans_of(empty).count() == 0
    assert toxicity.scored(empty.drop("score"), toxicity.train(spark, empty, labels)).count() == 0
    assert url_filter.judge(spark, spark.createDataFrame([], "page_id long, url string")).count() == 0


def test_one_of_each(spark, docs, rows):
    kept = sorted(map(repr, (tuple(r) for r in simhash.one_of_each(spark, docs).select("doc_id", "text").collect())))
    rng = random.Random(5)
    base = [f"w{rng.randint(0, 10**6)}" for _ in range(300)]
    near, far = list(base), [f"v{rng.randint(0, 10**6)}" for _ in range(300)]
    near[100] = "other"
    small = spark.createDataFrame([(1, " ".join(base)), (2, " ".join(near)), (3, " ".join(far)), (3, " ".join(far))], "doc_id long, text string")
    assert sorted(r.doc_id for r in simhash.one_of_each(spark, small).collect()) == [1, 3]
    texts = {t or "" for _, t in rows}
    assert len(kept) <= len(texts) and any("no id here" in x for x in kept)


def test_near_duplicates_stage_has_recall_and_precision_one(spark):
    """Against brute force on exact shingle sets: texts of all lengths, pairs on both sides of 0.8, a chain and many near copies."""
    rng = random.Random(12)
    say = lambda n: [f"w{rng.randint(0, 3000)}" for _ in range(n)]
    texts, footer = [], say(12)
    for n in (3, 6, 10, 12, 30, 60, 200):
        for changes in range(1, 8):
            for _ in range(6):
                one = say(n)
                other = list(one)
                for _ in range(changes):
                    other[rng.randrange(n)] = f"x{rng.randint(0, 3000)}"
                texts += [one + footer * (n == 60), other + footer * (n == 60)]
    many = say(80)
    texts += [[*many[:k], f"y{k}", *many[k + 1 :]] for k in range(0, 80)] + [many[k:] + say(k) for k in range(1, 12)]
    ten = say(10)
    texts += [ten, [*ten[:-1], "last"]]  # Jaccard 5 / 7: both stay
    rng.shuffle(texts)
    docs = spark.createDataFrame([(k, " ".join(t)) for k, t in enumerate(texts)], "doc_id long, text string")
    sets = [{tuple(t[i : i + 5]) for i in range(max(len(t) - 4, 1))} for t in texts]
    root = list(range(len(texts)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            common = len(sets[i] & sets[j])
            if common * 5 >= len(sets[i] | sets[j]) * 4:
                p, q = sorted((find(i), find(j)))
                root[q] = p
    kept = sorted(r.doc_id for r in simhash.one_of_each(spark, docs).collect())
    assert kept == sorted({find(i) for i in range(len(texts))})


def test_substring_dedup_runs_cut_at_the_edge_of_a_copy(spark):
    """A passage that ends or starts in a run which only one copy's neighbours extend."""
    rng = random.Random(21)
    say = lambda n: [f"v{rng.randint(0, 10**9)}" for _ in range(n)]
    texts = []
    for k in range(240):
        dot, size = rng.choice([".", "|", "-"]), rng.choice([35, 36, 60])
        few = [dot] * rng.randint(1, 3)
        passage = few + say(size - len(few)) if k % 2 else say(size - len(few)) + few
        more = [dot] * rng.randint(1, 12)
        for extra in ([], more):
            texts.append([*say(20), *extra, *passage, *say(20)] if k % 2 else [*say(20), *passage, *extra, *say(20)])
    seen = Counter(tuple(w[k : k + 35]) for w in texts for k in range(len(w) - 34))
    expected = []
    for key, w in enumerate(texts):
        gone = set()
        for k in range(len(w) - 34):
            if seen[tuple(w[k : k + 35])] > 1:
                gone |= set(range(k, k + 35))
        expected.append((key, len(gone)))
    docs = spark.createDataFrame([(k, " ".join(w)) for k, w in enumerate(texts)], "doc_id long, text string")
    assert min(n for _, n in expected) >= 35
    assert as_set(substring_dedup.repeated_words(spark, docs), "doc_id", "n_removed") == sorted(map(repr, expected))


def test_decontamination_cuts_the_same_in_any_number_of_blocks(spark):
    """Passages of items of different blocks overlap in a document, and a cut's seam joins an item's words."""
    rng = random.Random(31)
    texts, bench = [], []
    for k in range(12):
        w = [f"{k}w{i}" for i in range(80)]
        texts.append(" ".join(w))
        bench += [" ".join(w[10:25]), " ".join(w[20:32]), " ".join(w[50:62]), " ".join(w[45:50] + w[62:68])]
    rng.shuffle(bench)
    docs = spark.createDataFrame([(k, t, 7) for k, t in enumerate(texts)] + [(99, None, None), (99, "clean", 3)], "doc_id long, text string, n_chars long")
    items = spark.createDataFrame(list(enumerate(bench)), "item_id long, text string")
    one = as_set(decontaminate.cleaned(spark, docs, items), "doc_id", "text")
    assert as_set(decontaminate.cleaned(spark, docs, items, block_bytes=400), "doc_id", "text") == one
    left = decontaminate.cleaned(spark, docs, items, block_bytes=400).filter("doc_id = 3").first()
    assert left.text.split() == [f"3w{i}" for i in range(80) if not (10 <= i < 32 or 50 <= i < 62)] and left.n_chars == len(left.text)


def test_pii_secrets_without_digits_and_ibans_before_words():
    kinds = lambda t: [(k, t[a:b]) for a, b, k, _ in pii.find_spans(t)]
    assert kinds("my password = correcthorsebattery, keep it") == [("secret", "correcthorsebattery")]
    for number, after in (("AT34 1904 3002 3457 3202", " BIC BKAUATWW"), ("BE68 5390 0754 7034", " EUR 20"), ("BE68 5390 0754 7034", " EURO"), ("ES91 2100 0418 4502 0005 1332", " BIC"), ("DE89 3704 0044 0532 0130 00", "")):
        assert ("iban", number) in kinds(f"IBAN {number}{after}"), number
    both = kinds("IBAN BE68 5390 0754 7034 AT34 1904 3002 3457 3202 and more")
    assert both == [("iban", "BE68 5390 0754 7034"), ("iban", "AT34 1904 3002 3457 3202")]
    assert kinds("IBAN AT35 1904 3002 3457 3202 BIC") == []


def test_simhash_query_format(spark, docs, rows, tmp_path):
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    found = simhash.op9_simhash(spark, str(tmp_path)).select("doc_id", "fingerprint").collect()
    assert sorted(map(repr, map(tuple, found))) == sorted(repr((k, f"{plain_fingerprint(t):016x}")) for k, t in rows)


def test_simhash_trees_find_what_all_pairs_find():
    rng = np.random.default_rng(3)
    base = rng.integers(0, 1 << 63, 40, np.uint64)
    points = np.unique([int(b) ^ sum(1 << int(x) for x in rng.choice(64, 3, replace=False)) for b in base for _ in range(20)]).astype(np.uint64)
    assert len(points) > 20 * simhash.LEAF  # several levels of the tree
    links = simhash.near(points[:, None], 4)
    near = np.bitwise_count(points[:, None] ^ points[None]) <= 4
    label = np.arange(len(points))
    for _ in range(len(points)):
        label = np.where(near, label[None], len(points)).min(axis=1)
    root = {k: k for k in range(len(points))}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in links:
        assert near[a, b] and find(a) != find(b)  # a forest
        root[max(find(a), find(b))] = min(find(a), find(b))
    assert [find(k) for k in range(len(points))] == label.tolist()


@pytest.mark.parametrize("blocks", [5, 6, 7])
def test_simhash_views_of_any_number_of_blocks(spark, blocks):
    rng = np.random.default_rng(blocks)
    fps = {int(b) ^ sum(1 << int(x) for x in rng.choice(64, rng.integers(0, 4), replace=False)) for b in rng.integers(0, 1 << 62, 8) for _ in range(30)}
    nodes = spark.createDataFrame([(f - (1 << 64) * (f >> 63),) for f in fps], "fp long")
    found = {r.node: r.root for r in simhash.components(spark, simhash.links(spark, nodes, blocks=blocks)).collect()}
    arr = np.array(sorted(f - (1 << 64) * (f >> 63) for f in fps), np.int64)
    near, label = np.bitwise_count(arr.view(np.uint64)[:, None] ^ arr.view(np.uint64)[None]) <= 4, np.arange(len(arr))
    for _ in range(len(arr)):
        label = np.where(near, label[None], len(arr)).min(axis=1)
    assert [found.get(x, x) for x in arr.tolist()] == arr[label].tolist()


def test_fingerprint_lanes_as_whole_numbers(spark, docs, rows):
    def lane(text, salt):
        return xxhash.xxh64(salt.to_bytes(4, "little"), seed=xxhash.xxh64(text.encode(), seed=42).intdigest()).intdigest()

    def plain(text):
        lines = text.split("\n")
        phrases = [p for p in re.split(r"\n|(?<=[adegimorsty.,;:!?])[ \t]+", text) if p]
        wide = [sum(lane(x, k) & 0xFFFFFFFF for x in lines) % (1 << 32) for k in range(multiset.EXACT)]
        bits = [[lane(p, 100 + w) for p in phrases] for w in range(multiset.LANES // 64)]
        narrow = [(2 * sum(h >> b & 1 for h in hs) - len(phrases)) % (1 << 16) for hs in bits for k in range(32) for b in (k, k + 32)]
        return "".join(f"{x:08x}" for x in wide) + "".join(f"{x:04x}" for x in narrow), np.array([x - 65536 * (x > 32767) for x in narrow], float)

    def alike(a, b):
        if (a == b).all():
            return 1.0
        size = np.sqrt((a @ a) * (b @ b))
        return 0.0 if size == 0 else float(np.clip(a @ b / size, 0, 1))

    ordered = sorted(((k, t or "") for k, t in rows if k is not None), key=lambda x: (-x[0], x[1]))
    ordered += [(k, t or "") for k, t in rows if k is None]
    following = {(k, t): ordered[(i + 1) % len(ordered)][1] for i, (k, t) in enumerate(ordered)}
    found = multiset.with_edits(spark, docs).collect()
    texts = dict(ordered)
    assert len(found) == len(rows)
    for r in found:
        text = texts[r.doc_id]
        after, half = following[(r.doc_id, text)], len(text) // 2
        if sum(k == r.doc_id for k, _ in ordered) > 1:
            continue  # which of repeated rows follows which is open
        edited = text[: len(text) - half] + after[:half]
        (own, a), (other, b), (_, c) = plain(text), plain(edited), plain(after)
        assert (r.fingerprint, r.edited_fingerprint) == (own, other), r.doc_id
        assert abs(r.near_edited - alike(a, b)) < 1e-9 and abs(r.near_next - alike(a, c)) < 1e-9


def test_toxicity_against_textbook_ftrl():
    rng = np.random.default_rng(1)
    rows = [(np.unique(rng.integers(0, 40, rng.integers(0, 12))), int(rng.random() < 0.3)) for _ in range(200)]
    alpha, beta, l1, l2, bias = 0.5, 1.0, 0.6, 0.1, 1 << toxicity.BITS
    z, n = Counter(), Counter()

    def weight(i):
        own = 0.0 if i == bias else l1
        return 0.0 if abs(z[i]) <= own else -(z[i] - math.copysign(own, z[i])) / ((beta + math.sqrt(n[i])) / alpha + l2)

    for _ in range(2):
        for at, label in rows:
            some = [*at.tolist(), bias]
            w = {i: weight(i) for i in some}
            g = 1 / (1 + math.exp(-sum(w.values()))) - label
            for i in some:
                sigma = (math.sqrt(n[i] + g * g) - math.sqrt(n[i])) / alpha
                z[i] += g - sigma * w[i]
                n[i] += g * g
    expected = {i: weight(i) for i in z if weight(i)}
    model = toxicity.ftrl(rows, epochs=2, alpha=alpha, beta=beta, l1=l1, l2=l2)
    assert model.at.tolist() == sorted(expected) and 0 < len(expected) < 41
    assert np.allclose(model.weights, [expected[i] for i in sorted(expected)], atol=1e-9)


def test_toxicity_features_are_words_pairs_and_skips():
    texts = [b"One two three two", None, b"", b"alone", b"a b"]
    at, doc = toxicity.features(texts)
    expected = []
    for k, t in enumerate(texts):
        w = (t or b"").lower().split()
        expected.append(len(w) + max(len(w) - 1, 0) + max(len(w) - 2, 0))
    assert np.bincount(doc, minlength=len(texts)).tolist() == expected
    assert len(set(at[doc == 0].tolist())) == 3 + 3 + 2  # distinct words, pairs, skips


def test_names_that_clash(spark):
    say = lambda n, seed: " ".join(random.Random(seed).choice(WORDS) + str(k) for k in range(n))
    rows = [(k, say(40, k % 3), 1.5, 7, 8, 9, 1, "n", b"x") for k in range(6)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, score double, _row int, _node int, _ROOT int, size int, node string, mark binary")
    left = simhash.one_of_each(spark, docs)
    assert left.columns == docs.columns and sorted(tuple(r) for r in left.collect()) == sorted((*r[:8], bytearray(r[8])) for r in rows[:3])
    model = toxicity.Model(np.array([1 << toxicity.BITS]), np.array([0.0]))
    told = toxicity.scored(docs, model)
    assert told.columns == [c for c in docs.columns if c != "score"] + ["score"] and {r.score for r in told.collect()} == {0.5}
    items = spark.createDataFrame([(1, " ".join(rows[0][1].split()[:12]))], "item_id long, text string")
    for size in (decontaminate.BLOCK_BYTES, 20):
        assert decontaminate.cleaned(spark, docs, items, block_bytes=size).columns == docs.columns
    assert pii.redacted(docs).columns == docs.columns


def test_pii_base_kinds_equal_the_plain_patterns():
    plain = {
        "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
        "ip": (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(p) <= 255 for p in m.split("."))),
        "card": (r"[0-9]([\x20-]?[0-9])+", lambda m: 14 <= len(d := re.sub("[^0-9]", "", m)) <= 19 and sum(sum(divmod(int(c) * (1 + k % 2), 10)) for k, c in enumerate(reversed(d))) % 10 == 0),
        "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 10 <= len(re.sub("[^0-9]", "", m)) <= 15),
    }
    rng = random.Random(8)
    pieces = ["0" * 45 + "1.2.3.4", "1.2.3." + "0" * 60 + "4", "256.1.1.1", "1.2.3.4.5.6.7.8", "a@b.c", "@", "x.y@z-w.org.", "4111 1111 1111 1111", "4111-1111", "+1 (269) 555-3296", "+", ".", " ", "-", "12", "٣.1.1.1", "é"]
    for _ in range(400):
        text = "".join(rng.choice(pieces) for _ in range(rng.randint(1, 9)))
        expected = sorted((m.start(), m.end(), kind) for kind, (p, good) in plain.items() for m in re.finditer(p, text) if good(m[0]))
        assert sorted(pii.base_spans(text)) == expected, text


def test_packing_bound_and_best_fit():
    rng = np.random.default_rng(5)
    for sizes in (rng.integers(1, 2049, 400), np.clip(rng.exponential(300, 3000), 1, 2048).astype(int), rng.integers(500, 1100, 2000), np.array([1025] * 10 + [1024] * 11)):
        counts = dict(zip(*(x.tolist() for x in np.unique(sizes, return_counts=True)), strict=True))
        made = packing.plan(counts, 2048, rounds=400)
        best = sum(n for _, n in packing._best_fit(dict(counts), 2048))
        assert max(-(-int(sizes.sum()) // 2048), made.bound) <= made.sequences <= best + 1 + best // 1000
    assert packing.plan({1025: 10, 1024: 11}, 2048).bound == 16  # above the 11 that tokens ask for
    assert packing.plan({}, 2048).sequences == 0


def test_url_threshold_against_all_thresholds(spark):
    rng = random.Random(2)
    for n, far in ((1, 0.0), (7, 1.0), (300, 0.3), (300, 50.0)):
        rows = [(k % 2, 1 - k % 2, round(rng.gauss(far * (k % 2), 1), 2)) for k in range(2 * n)]
        good, bad = [s for a, _, s in rows if a], [s for _, b, s in rows if b]
        gap = lambda t: abs(sum(s < t for s in good) / len(good) - sum(s >= t for s in bad) / len(bad))
        found = url_filter.calibrate(spark.createDataFrame(rows, "accepted int, rejected int, score double"), bins=5)
        assert gap(found) <= min(gap(t) for _, _, t in rows) + 1e-12
    assert url_filter.calibrate(spark.createDataFrame([(1, 0, 0.5)], "accepted int, rejected int, score double")) == 0.0


def test_windows_of_equal_first_halves_are_told_apart(spark):
    names, checks = np.array([5, 5, 9, 5, (1 << 64) - 1], np.uint64), np.array([1, 2, 3, 1, 4], np.uint64)
    assert substring_dedup._numbers(names, checks).tolist() == [0, 1, 2, 0, 3]
    assert substring_dedup._numbers(names).tolist() == [0, 0, 1, 0, 2]
    edges = substring_dedup._edges(3)
    sent = [r for unit, some in ((7, [0, 1]), (8, [1, 2, 4]), (9, [4])) for r in substring_dedup._pack(unit, edges, names[some], checks[some])]
    rows = [(r["part"], r["unit"], bytearray(r["names"]), bytearray(r["checks"]), bytearray(r["more"])) for r in sent]
    told = {r.unit: substring_dedup._flags(r.told).tolist() for r in substring_dedup._repeated(spark.createDataFrame(rows, substring_dedup._SENT_SQL), 3).collect()}
    assert told == {7: [False, True], 8: [True, False, True], 9: [True]}  # (5, 2) and the last name are twice there, (5, 1) isn't


def test_token_store_splits_a_hot_key(spark, tmp_path):
    texts = [f"{k % 7} words {k}" for k in range(300)] + ["same"] * 300
    docs = spark.createDataFrame([(5, t) for t in texts] + [(k, f"doc {k}") for k in (1, 9)], "doc_id long, text string").repartition(4)
    manifest = token_store.write_store(spark, docs, public_tokenizers.path("byte_bpe_50k.json"), str(tmp_path), 2, shards=6)
    assert max(s["docs"] for s in manifest["shards"]) < 300
    found = sorted(token_store.read_store(spark, str(tmp_path), manifest).collect(), key=lambda r: r.start)
    assert [r.doc_id for r in found] == [1] + [5] * 600 + [9]
    assert [r.start for r in found[1:]] == [r.start + r.n_tokens for r in found[:-1]]
    assert len(token_store.lookup(str(tmp_path), manifest, 5)) == 600 and len(token_store.lookup(str(tmp_path), manifest, 9)) == 1


def test_token_store_reads_in_blocks():
    starts = np.array([0, 3, 3, 10, 50, 51])
    blocks = [x.tolist() for x in token_store._blocks(np.arange(5), starts, 10)]
    assert blocks == [[0, 1, 2], [3], [4]] and [x.tolist() for x in token_store._blocks(np.arange(5), starts, 1)] == [[0], [1], [2], [3], [4]]


def test_pii_counts_and_hash_are_of_base_spans_alone(spark, tmp_path):
    text = "4524132264652876 4111 1111 1111 1111 or +1 269 555 3296 4111 1111 1111 1111"  # two cards and a phone hidden in matches that fail
    spark.createDataFrame([(1, text), (2, "card 4111 1111 1111 1111"), (3, None)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    found = {r.doc_id: r for r in pii.op6_pii(spark, str(tmp_path)).collect()}
    none = hashlib.sha256(b"").hexdigest()
    assert (found[1].n_card, found[1].n_phone, found[1].base_sha256) == (0, 0, none) and "card:" in found[1].spans
    assert (found[2].n_card, found[2].base_sha256) == (1, hashlib.sha256(b"card:5:24").hexdigest()) and found[3].base_sha256 == none


def test_near_duplicates_stage_links_by_fingerprints_first(spark, monkeypatch):
    """Near copies are linked by SimHash alone; the prefix join is left with pairs of different groups."""
    rng = random.Random(33)
    say = lambda n: [f"w{rng.randint(0, 10**6)}" for _ in range(n)]
    base, seen = say(900), []
    texts = [[*base[:k], "other", *base[k + 1 :]] for k in (10, 400, 880)] + [say(60), say(60)]
    proposed = simhash._proposed
    monkeypatch.setattr(simhash, "_proposed", lambda shards, chosen: seen.append(shards.count()) or proposed(shards, chosen))
    docs = spark.createDataFrame([(k, " ".join(t)) for k, t in enumerate(texts)], "doc_id long, text string")
    assert sorted(r.doc_id for r in simhash.one_of_each(spark, docs).collect()) == [0, 3, 4] and seen == [0, 0]
    hashes = np.array([0b101, 0b100, 0b110], np.uint64)
    assert simhash.majority(hashes) == 0b100 and simhash.majority(hashes[:0]) == 0 and simhash.majority(hashes[1:]) == 0b100


def test_near_duplicates_stage_deals_out_no_text_to_pick_rows(spark, monkeypatch):
    """Rows are picked by bits of their numbers, without a shuffle of them; beyond WORDS a join by number gives the same."""
    numbers = spark.range(1000).selectExpr("id as _at", "'text' as _bits")
    some = spark.range(1000).filter("id % 7 = 0 or id in (63, 64, 127)").union(spark.range(1)).selectExpr("id as which")
    want = [k for k in range(1000) if k % 7 == 0 or k in (63, 64, 127)]
    monkeypatch.setattr(simhash, "WORDS", 2)
    assert sorted(r._at for r in simhash.among(numbers, "_at", some, partial(simhash.materialise, spark)).collect()) == want
    monkeypatch.undo()
    docs = spark.createDataFrame([(k, f"{k % 9} words of a text of its own") for k in range(20)], "doc_id long, text string")
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")  # as for large tables
    try:
        assert sorted(r._at for r in simhash.among(numbers, "_at", some, partial(simhash.materialise, spark)).collect()) == want
        left = simhash.one_of_each(spark, docs)
        plan = left._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    assert "hashpartitioning" not in plan and sorted(r.doc_id for r in left.collect()) == list(range(9))
