"""The operators on small tables, against brute force, with awkward rows."""

import gzip
import hashlib
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest

from driftclust.llm import decontaminate, exact_dedup, graph, jaccard_join, kernels, packing, pii, quality, substring_dedup, suffix_array, token_files, tokens, toxicity, warc

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, cid long, n long, y int, token string"


def docs_of(spark, texts, first=0):
    rows = [(first + i, t, "en", "s", 0, 7, 7, 7, "x") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, SCHEMA)


def words(rng, n, size=400):
    return [f"w{rng.randrange(size)}" for _ in range(n)]


@pytest.fixture(scope="module")
def awkward():
    """Null, empty, blank, short, very long, copies, a group of near copies."""
    rng = random.Random(5)
    base = words(rng, 300, 5000)
    out = [None, "", " \n\t ", "one", "One", "two words", "ünï cödé ßtraße ça va bien", "a" * 5000, " ".join(words(rng, 30000, 9000))]
    out += [" ".join(base)] * 40
    for k in range(60):
        near = list(base)
        for j in rng.sample(range(300), 1 + k % 7):
            near[j] = f"new{k}x{j}"
        out.append(" ".join(near))
    out += [" ".join(words(rng, rng.randint(5, 200), 3000)) + " " + " ".join(base[:90]) for _ in range(30)]
    out += [" ".join(words(rng, rng.randint(1, 120), 3000)) for _ in range(60)]
    rng.shuffle(out)
    return out


def test_exact_dedup(spark, awkward):
    got = {r.doc_id: r for r in exact_dedup.classes(docs_of(spark, awkward)).collect()}
    groups = defaultdict(list)
    for i, t in enumerate(awkward):
        groups[t or ""].append(i)
    for t, ids in groups.items():
        for i in ids:
            r = got[i]
            assert (r.keep_id, r.group_size, r.kept) == (max(ids), len(ids), i == max(ids))
            assert r.text_sha256 == hashlib.sha256(t.encode()).hexdigest()
    left = exact_dedup.drop_copies(docs_of(spark, awkward))
    assert left.columns == docs_of(spark, []).columns
    assert sorted(r.doc_id for r in left.collect()) == sorted(max(v) for v in groups.values())


def shingle_set(t):
    import re

    w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate({i: i + 32 for i in range(65, 91)}))
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


def brute_components(texts):
    sets = [shingle_set(t) for t in texts]
    root = list(range(len(texts)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(texts)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if both and 100 * both >= 80 * (len(sets[i]) + len(sets[j]) - both):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return {i: (len(sets[i]), find(i)) for i in range(len(texts))}


def test_jaccard_join(spark, awkward):
    want = brute_components(awkward)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_join.near_copies(docs_of(spark, awkward)).collect()}
    assert got == want
    left = jaccard_join.keep_one(docs_of(spark, awkward))
    assert left.columns == docs_of(spark, []).columns
    assert {r.doc_id for r in left.collect()} == {i for i, (_, c) in want.items() if i == c}


def test_jaccard_join_on_chains_of_near_copies(spark):
    """Each text is near its neighbours only; links must not stop at the first."""
    rng = random.Random(8)
    w, texts = words(rng, 120, 10**6), []
    for k in range(80):
        texts.append(" ".join(w))
        for j in range(2):
            w[(k * 7 + j * 31) % 120] = f"z{k}_{j}"
    order = list(range(80))
    rng.shuffle(order)
    texts = [texts[i] for i in order]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_join.near_copies(docs_of(spark, texts)).collect()}
    assert got == brute_components(texts)


def test_components(spark):
    rng = random.Random(2)
    edges = [(i, i + 1) for i in range(300)] + [(1000, rng.randrange(1001, 1100)) for _ in range(80)] + [(5000, 5000), (7, 7)]
    got = {r.node: r.root for r in graph.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(301)) and all(v == 1000 for k, v in got.items() if k >= 1000)


def test_decontamination(spark):
    rng = random.Random(3)
    items = [words(rng, n, 10**6) for n in (8, 20, 60, 200)] + [["just", "Three", "words"], []]
    table = spark.createDataFrame([(i, " ".join(w) if w else None, 1) for i, w in enumerate(items)], "item_id long, text string, sh int")
    texts = [None, "", "just three WORDS", "just three words more", " ".join(items[2]), " ".join(words(rng, 5000) + items[1] + words(rng, 5000)), " ".join(items[3][:150]), " ".join(items[3][:170] + words(rng, 30)), " ".join(words(rng, 300))]
    want = set()
    for d, t in enumerate(texts):
        s = shingle_set(t)
        for i, w in enumerate(items):
            q = shingle_set(" ".join(w))
            if q and 1000 * len(s & q) >= 800 * len(q):
                want.add((d, i, len(q), len(s & q)))
    got = {(r.doc_id, r.item_id, r.n_item, r.n_shared) for r in decontaminate.matches(docs_of(spark, texts), table).collect()}
    assert got == want and (5, 1, 16, 16) in got and (2, 4, 1, 1) in got
    left = decontaminate.remove_contaminated(docs_of(spark, texts), table)
    assert {r.doc_id for r in left.collect()} == set(range(len(texts))) - {d for d, *_ in want}


def test_decontamination_of_a_document_in_two_rows(spark):
    w = words(random.Random(4), 40, 10**6)
    table = spark.createDataFrame([(7, " ".join(w))], "item_id long, text string")
    docs = spark.createDataFrame([(1, " ".join(w[:22])), (1, " ".join(w[18:])), (2, " ".join(w[:22]))], "doc_id long, text string")
    assert [(r.doc_id, r.n_shared) for r in decontaminate.matches(docs, table).collect()] == [(1, 36)]


def test_suffix_array_is_sorted():
    rng = np.random.default_rng(0)
    for n, a in ((1, 3), (60, 2), (300, 3), (700, 5)):
        t = np.append(rng.integers(1, 1 + a, n), 0).astype(np.uint8)
        b = t.tobytes()
        assert suffix_array.suffix_array(t, n + 8).tolist() == sorted(range(len(b)), key=lambda i: b[i:])


def brute_repeats(texts, depth):
    raw = [(t or "").encode() for t in texts]
    seen = Counter(b[i : i + depth] for b in raw for i in range(len(b) - depth + 1))
    out = []
    for b in raw:
        gone = bytearray(len(b))
        for i in range(len(b) - depth + 1):
            if seen[b[i : i + depth]] > 1:
                gone[i : i + depth] = b"\1" * depth
        n = sum(1 for i in range(len(b)) if gone[i] and (i == 0 or not gone[i - 1]))
        out.append((len(b), sum(gone), n, hashlib.sha256(bytes(x for x, g in zip(b, gone, strict=True) if not g)).hexdigest()))
    return out


def test_substring_dedup(spark, awkward, monkeypatch):
    texts = [t for t in awkward if len(t or "") < 20000]
    passage = "".join(random.Random(1).choice("abcdefgh \0é") for _ in range(700))
    texts += [f"{i} " * 50 + passage[i : i + 500] + f" {i}" * 60 for i in range(0, 60, 3)] + [passage * 2, passage[:399], passage[:400]]
    want = brute_repeats(texts, 400)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in substring_dedup.digests(docs_of(spark, texts)).collect()}
    assert [got[i] for i in range(len(texts))] == want
    monkeypatch.setattr(substring_dedup, "CROWDED", 5)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in substring_dedup.digests(docs_of(spark, texts)).collect()}
    assert [got[i] for i in range(len(texts))] == want


def test_substring_dedup_of_rows_alike_in_id_and_text(spark):
    t = "".join(random.Random(4).choice("abcdefgh ") for _ in range(900))
    df = spark.createDataFrame([(1, t), (1, t), (2, "x" * 500)], "doc_id long, text string")
    got = sorted((r.doc_id, r.n_removed) for r in substring_dedup.digests(df).collect())
    assert got == [(1, 900), (1, 900), (2, 500)]


def test_tokens_equal_the_library(awkward):
    e = tokens.encoder(tokens.default_path())
    rng = random.Random(1)
    parts = ["a", "b", "s", "t", "re", "'", "'s", "'ll", " ", "  ", "\n", "\t", "1", "é", "!", "..", "中", "\xa0", "😀", "\x85", "<|endoftext|>", "²", "don't", "_"]
    texts = awkward + ["".join(rng.choice(parts) for _ in range(rng.randint(0, 40))) for _ in range(3000)]
    ids, off = e.encode(pa.array(texts))
    for i, enc in enumerate(e.tokenizer.encode_batch([t or "" for t in texts], add_special_tokens=False)):
        assert ids[off[i] : off[i + 1]].tolist() == enc.ids


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def test_token_files(spark, awkward):
    rng = np.random.default_rng(0)
    v = rng.integers(0, 1 << 32, 1001, dtype=np.uint64).astype(np.uint32) >> rng.integers(0, 32, 1001).astype(np.uint32)
    for part in (v, v[:0], v[:3]):
        assert (token_files.unpack(*token_files.pack(part), len(part)) == part).all()
    lib = tokens.encoder(tokens.default_path()).tokenizer
    start, want = 0, []
    for i, t in enumerate(awkward):
        ids = [*lib.encode(t or "", add_special_tokens=False).ids, 0]
        want.append((i, start, len(ids), crc(ids)))
        start += len(ids)
    assert sorted(tuple(r) for r in token_files.round_trip(docs_of(spark, awkward)).collect()) == want


def test_packing(spark, awkward):
    lib = tokens.encoder(tokens.default_path()).tokenizer
    rows = packing.pack_documents(docs_of(spark, awkward)).collect()
    by = defaultdict(list)
    for r in rows:
        by[r.doc_id].append(r)
    total = 0
    for i, t in enumerate(awkward):
        ids = [*lib.encode(t or "", add_special_tokens=False).ids, 2]
        total += len(ids)
        at = 0
        for k, r in enumerate(sorted(by[i], key=lambda r: r.piece)):
            assert (r.piece, r.start, r.ids_crc32) == (k, at, crc(ids[at : at + r.length])) and (k == 0 or r.length == 1024)
            at += r.length
        assert at == len(ids)
    seq = defaultdict(list)
    for r in rows:
        seq[r.sequence_id].append((r.offset, r.length))
    for parts in seq.values():
        end = 0
        for o, n in sorted(parts):
            assert o == end
            end = o + n
        assert end <= 1024
    # Pieces over half a sequence can't share one: another lower bound.
    assert len(seq) <= 1.05 * max(total / 1024, sum(r.length > 512 for r in rows)) + 1


@pytest.mark.parametrize("seed", range(4))
def test_layouts_place_every_piece(seed):
    rng = np.random.default_rng(seed)
    h = np.bincount(rng.integers(1, 101, 300), minlength=101)
    got, bins = np.zeros(101, int), 0
    for lengths, times in packing.layouts(h, 100):
        assert sum(lengths) <= 100 and times > 0
        bins += times
        for x in lengths:
            got[x] += times
    assert (got == h).all() and bins <= 1.06 * (h * np.arange(101)).sum() / 100 + 1


def test_exact_pairs_are_fixed():
    h = np.zeros(101, int)
    h[[60, 40, 70, 30, 100]] = [3, 3, 2, 2, 1]
    assert sum(n for _, n in packing.layouts(h, 100)) == 6


@pytest.mark.parametrize("seed", range(3))
def test_layouts_are_best_fit_at_least(seed):
    """Piece by piece best fit, longest first, never takes fewer sequences."""
    rng = np.random.default_rng(seed)
    for _ in range(20):
        sizes = rng.integers(1, rng.integers(20, 101), rng.integers(1, 200))
        bins: list[int] = []
        for x in sorted(sizes.tolist(), reverse=True):
            fits = [i for i, level in enumerate(bins) if level + x <= 100]
            if fits:
                bins[max(fits, key=lambda i: bins[i])] += x
            else:
                bins.append(x)
        h = np.bincount(sizes, minlength=101)
        assert sum(n for _, n in packing.best_fit(h, 100)) == len(bins)
        assert sum(n for _, n in packing.layouts(h, 100)) <= len(bins)


def test_three_pieces_are_fixed():
    h = np.zeros(101, int)
    h[[60, 25, 14, 90]] = [1, 1, 1, 1]
    fixed = packing.reduce(h, 100)
    assert sorted(lengths for lengths, _ in fixed) == [(60, 25, 14), (90,)] and not h.any()


def test_reduction_keeps_an_optimum():
    """Against the least number of sequences, found by trying all ways."""
    from functools import cache

    @cache
    def least(left: tuple[int, ...]) -> int:
        if not left:
            return 0
        first, rest, best = left[0], left[1:], 99
        for mask in range(1 << len(rest)):
            if first + sum(x for i, x in enumerate(rest) if mask >> i & 1) <= 20:
                best = min(best, 1 + least(tuple(x for i, x in enumerate(rest) if not mask >> i & 1)))
        return best

    rng = random.Random(5)
    for _ in range(150):
        sizes = tuple(sorted((rng.randint(1, 15) for _ in range(rng.randint(1, 8))), reverse=True))
        h = np.bincount(sizes, minlength=21)
        fixed = packing.reduce(h, 20)
        left = tuple(x for x in range(20, 0, -1) for _ in range(h[x]))
        assert sum(n for _, n in fixed) + least(left) == least(sizes), sizes


def test_warc(spark):
    pages = [(5, "http://a/é x\r\n", "<p>one</p>"), (3, "http://b", "<p>one</p>"), (9, None, None), (1, "http://c", ""), (8, "http://d", "<p>two</p>\r\n\r\nmore"), (2**40, "http://e", "<p>one</p>")]
    df = spark.createDataFrame([(*p, "extra") for p in pages], "page_id long, url string, html string, first_id string")
    folder = warc.new_dir(spark, "warc")
    index = warc.write(df, folder)
    got = {r.page_id: r for r in warc.read(index, folder, payloads=True).collect()}
    first = {"<p>one</p>": 3, "": 1}
    for page_id, _, html in pages:
        r, want = got[page_id], first.get(html or "", page_id)
        assert r.record_type == ("response" if want == page_id else "revisit") and r.refers_to == (None if want == page_id else want)
        assert r.payload_bytes == len((html or "").encode()) and r.payload_digest == warc.digest_of((html or "").encode())
        assert r.payload is None or bytes(r.payload) == (html or "").encode()
    one = index.where("page_id = 8")
    assert [r.page_id for r in warc.read(one, folder).collect()] == [8]
    fs, place = warc.open_store(folder)
    row = one.first()
    with fs.open_input_file(f"{place}/{row.file}") as f:
        f.seek(row.offset)
        assert gzip.decompress(f.read(row.length)).startswith(b"WARC/1.1\r\nWARC-Type: response")


def test_pii_base_spans_equal_the_patterns():
    import re

    e, i, c, h = (re.compile(p) for p in (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"[0-9]([\x20-]?[0-9])+", r"\+[0-9][\x20().0-9-]+[0-9]"))
    only = lambda t: re.sub("[^0-9]", "", t)
    rng = random.Random(3)
    parts = ["@", "a", "b.c", ".", "-", "1", "23", "4", "256", " ", "+", "(", ")", "0", "é", "%", "\n", "4111111111111111", "٣", "10.0.0.1", "+1 (555) 123-4567"]
    for _ in range(4000):
        t = "".join(rng.choice(parts) for _ in range(rng.randint(0, 30)))
        want = [(m.start(), 0, m.end()) for m in e.finditer(t)] + [(m.start(), 1, m.end()) for m in i.finditer(t) if all(int(x) <= 255 for x in m[0].split("."))]
        want += [(m.start(), 2, m.end()) for m in c.finditer(t) if 12 <= len(only(m[0])) <= 19 and pii._luhn(only(m[0]))] + [(m.start(), 3, m.end()) for m in h.finditer(t) if 9 <= len(only(m[0])) <= 15]
        assert pii.base_spans(t) == sorted(want), t


def test_pii_crf_finds_forms_that_patterns_miss(spark):
    texts = [None, "", "the of and " * 300, 'é token = "8a780956d7b276b8f9fff5f9208f67555b1c8245" on', "call (415) 555-0132 now", "mail é.x@mail.example.com today", "word " * 20000]
    got = {r.doc_id: r for r in pii.find(docs_of(spark, texts)).collect()}
    assert got[0].spans == got[1].spans == got[2].spans == got[6].spans == "" and got[0].base_sha256 == hashlib.sha256(b"").hexdigest()
    assert got[3].spans == "secret:11:51" and got[4].spans.startswith("phone:5:") and got[5].n_email == 1 and "email:6:25" in got[5].spans


def test_viterbi_equals_enumeration():
    import itertools

    rng = np.random.default_rng(1)
    em, step = rng.normal(size=(4, 5, 3)).astype(np.float32), rng.normal(size=(3, 3)).astype(np.float32)
    live = np.ones((4, 5), bool)
    live[1, 3:] = False
    got = pii.viterbi(em, live, step)
    for s in range(4):
        n = int(live[s].sum())
        best = max(itertools.product(range(3), repeat=n), key=lambda y: sum(em[s, i, v] for i, v in enumerate(y)) + sum(step[a, b] for a, b in zip(y, y[1:], strict=False)))
        assert got[s, :n].tolist() == list(best)


def test_classifiers_on_held_out_rows(spark, sf):
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    for module, label in ((toxicity, "toxic"), (quality, "quality")):
        r = module.score(docs, module.train(docs, labels)).join(labels, "doc_id").where("held_out").toPandas()
        assert ((r["predicted"] == r[label]).mean()) > 0.9 and r["score"].between(0, 1).all()
        again = module.score(docs, module.train(docs.repartition(5), labels)).where("doc_id < 20").toPandas().sort_values("doc_id")
        once = module.score(docs, module.train(docs, labels)).where("doc_id < 20").toPandas().sort_values("doc_id")
        assert np.allclose(again["score"], once["score"])


def test_quality_learns_from_every_labelled_row_and_pair(spark):
    """More labelled rows than the sample that was drawn before; slope by all pairs."""
    rng = np.random.default_rng(3)
    n, d = 20_500, len(quality.features.STYLE)
    y = rng.integers(0, 2, n)
    x = rng.random((n, d)) + 0.5 * y[:, None] * (np.arange(d) < 2)
    rows = spark.createDataFrame([(int(a), r.tobytes()) for a, r in zip(y, x, strict=True)], "y int, x binary")
    m = quality.bradley_terry(rows.repartition(3))
    full = quality.expand(x)
    assert np.allclose(m.mean, full.mean(axis=0)) and np.allclose(m.scale, full.std(axis=0))
    z = (full - m.mean) / m.scale
    raw = z @ m.weight
    edge = np.quantile(raw, (y == 0).mean())
    assert np.log(0.3 / 0.7) - m.shift == pytest.approx((edge + raw[raw > edge].min()) / 2, abs=1e-9)
    good, bad = z[y == 1], z[y == 0]
    slope = np.zeros(2 * d)
    for lo in range(0, len(good), 1000):
        part = 1 / (1 + np.exp(np.subtract.outer(good[lo : lo + 1000] @ m.weight, bad @ m.weight)))
        slope += part.sum(axis=0) @ bad - part.sum(axis=1) @ good[lo : lo + 1000]
    assert np.abs(slope / len(good) / len(bad) + 1e-4 * m.weight).max() < 2e-3


def test_classifiers_without_labels_and_with_awkward_texts(spark, awkward):
    none = spark.createDataFrame([], "doc_id long, toxic int, quality int")
    docs = docs_of(spark, awkward)
    for module in (toxicity, quality):
        rows = module.score(docs, module.train(docs, none)).collect()
        assert len(rows) == len(awkward) and all(r.score == pytest.approx(0.5) for r in rows)


def test_empty_tables(spark):
    empty = docs_of(spark, [])
    items = spark.createDataFrame([], "item_id long, text string")
    for df in (exact_dedup.classes(empty), exact_dedup.drop_copies(empty), jaccard_join.near_copies(empty), jaccard_join.keep_one(empty), decontaminate.matches(empty, items), substring_dedup.digests(empty), token_files.round_trip(empty), packing.pack_documents(empty), pii.find(empty)):
        assert df.count() == 0
    assert warc.round_trip(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_word_kernel_respects_rows():
    data, off = kernels.utf8(pa.array(["ab cd", "ef", None, " gh "]))
    s, e = kernels.words(data, off)
    assert [data[a:b].tobytes() for a, b in zip(s, e, strict=True)] == [b"ab", b"cd", b"ef", b"gh"]


@pytest.mark.parametrize("crowd, block", [(2, 4), (3, 8)])
def test_jaccard_join_in_blocks(spark, monkeypatch, crowd, block):
    """Groups of near copies of which not all are links, met in several blocks."""
    monkeypatch.setattr(jaccard_join, "CROWD", crowd)
    monkeypatch.setattr(jaccard_join, "BLOCK_CLASSES", block)
    monkeypatch.setattr(jaccard_join, "MATCHES", 64)
    rng = random.Random(crowd)
    texts = []
    for g in range(4):
        w = words(rng, 90 + 20 * g, 10**6)
        for k in range(24):
            own = list(w)
            for _ in range(rng.randrange(8)):
                own[rng.randrange(len(own))] = f"y{g}_{k}_{rng.random()}"
            texts.append(" ".join(own))
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_join.near_copies(docs_of(spark, texts)).collect()}
    want = brute_components(texts)
    assert got == want and len({c for _, c in want.values()}) > 4


def test_jaccard_join_writes_blocks_and_sets_once(spark, monkeypatch):
    """However many pairs of blocks meet, the rows shuffled for them hold no sets."""
    monkeypatch.setattr(jaccard_join, "CROWD", 2)
    monkeypatch.setattr(jaccard_join, "BLOCK_CLASSES", 4)
    kept, sent, keep, sides = [], [], jaccard_join._keep, jaccard_join._sides
    monkeypatch.setattr(jaccard_join, "_keep", lambda *a: kept.append((r := keep(*a))[0].select("key").collect()) or r)
    monkeypatch.setattr(jaccard_join, "_sides", lambda rows, kernel, payload, *a: sent.append((payload, bool(a[1:]))) or sides(rows, kernel, payload, *a))
    rng = random.Random(5)
    w = words(rng, 100, 10**6)
    texts = [" ".join(f"y{k}_{i}" if rng.random() < 0.03 else x for i, x in enumerate(w)) for k in range(40)]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_join.near_copies(docs_of(spark, texts)).collect()}
    assert got == brute_components(texts)
    assert len(kept) == 3 and all(len(k) == len(set(k)) for k in kept)
    assert [p for p, filed in sent if not filed] == [("n", "l", "prefix")]  # blocks by themselves


def test_sketch_of_frequencies_grows_with_the_texts():
    bits = [jaccard_join.sketch_bits(n) for n in (0, 10**8, 5 * 10**8, 10**9, 6 * 10**9)]
    assert bits == [22, 22, 25, 25, 25]
    s = np.arange(40, dtype=np.uint64) << np.uint64(58)
    for b in (22, 24):  # cells are numbered by as many bits as there are cells
        kinds = np.zeros(1 << b, np.uint8)
        kinds[0] = 9
        assert s[0] not in jaccard_join.prefix(s, kinds, 80)[1]


def test_token_files_order_repeated_ids_by_text(spark, tmp_path):
    """Ids beyond 65535 keep their value, too."""
    path = tokens.default_path()
    rows = [(1, "b x"), (2, "zz"), (1, "a long text"), (1, None), (3, "a"), (1, "b")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert token_files.encoded(df, path, 0).count() == 6
    got = token_files.read(token_files.write(df, str(tmp_path), path, 70_000), str(tmp_path)).orderBy("start").collect()
    want = [(k, np.append(tokens.encoder(path).encode(pa.array([t]))[0], 70_000)) for k, t in sorted((k, t or "") for k, t in rows)]
    assert [(r.doc_id, np.frombuffer(r.ids, "<u4").tolist()) for r in got] == [(k, i.tolist()) for k, i in want]


def test_writing_token_files_takes_encoded_rows(spark, tmp_path, monkeypatch):
    made, real = [], token_files.encoded
    monkeypatch.setattr(token_files, "encoded", lambda *a: made.append(real(*a)) or made[-1])
    monkeypatch.setattr(token_files, "ranking", lambda rows, f=token_files.ranking: f(rows) if rows is made[-1] else None)
    token_files.write(docs_of(spark, ["a b", "c"]), str(tmp_path), tokens.default_path())
    assert len(made) == 1 and "text" not in made[0].columns
