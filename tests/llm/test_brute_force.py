"""Each operator against a plain version of itself, on small tables with odd rows."""

import hashlib
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

WORDS = [f"w{i}x" for i in range(400)]


def prose(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n))


def frame(spark, rows):
    """Rows of (id, text) with columns that clash with names used inside."""
    return spark.createDataFrame([(i, t, "l", "s", len(t or ""), 1) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long, bucket int")


ODD = [(9001, None), (9002, ""), (9003, " \n "), (9004, "one"), (9005, "two words"), (9006, "é日本 ▁ x"), (9007, "long " * 3000)]


@pytest.fixture(scope="module")
def texts():
    rng = random.Random(4)
    rows = [(i, prose(rng, rng.choice([5, 40, 120]))) for i in range(60)]
    base = prose(rng, 150).split()
    for i in range(25):  # near copies at several distances, and exact ones
        own = list(base)
        for j in rng.sample(range(150), i % 9):
            own[j] = f"e{i}_{j}"
        rows.append((100 + i, " ".join(own)))
    rows += [(200 + i, rows[3][1]) for i in range(3)]
    return rows + ODD


def shingles(text, k, fold=True):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", low)
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set()


def groups(links, ids):
    parent = {i: i for i in ids}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


@pytest.mark.parametrize("k,percent", [(3, 85), (5, 80)])
def test_near_duplicates(spark, texts, k, percent):
    from variety.llm.near_duplicates import near_duplicates

    sets = {i: shingles(t, k) for i, t in texts}
    ids = [i for i, _ in texts]
    links = [(a, b) for n, a in enumerate(ids) for b in ids[:n] if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    want = groups(links, ids)
    got = {r["doc_id"]: r for r in near_duplicates(frame(spark, texts), k, percent).collect()}
    assert {i: r["component_id"] for i, r in got.items()} == want
    assert {i: r["n_shingles"] for i, r in got.items()} == {i: len(s) for i, s in sets.items()}


def test_near_duplicates_of_nothing(spark):
    from variety.llm.near_duplicates import near_duplicates

    assert near_duplicates(frame(spark, [])).count() == 0
    got = near_duplicates(frame(spark, [(None, "a b c"), (1, "a b c"), (1, "a b c")])).collect()
    assert len(got) == 3 and all(r["kept"] for r in got)


def test_sketches_fill_and_estimate():
    from variety.llm.near_duplicates import _FREE, sketches

    rng = np.random.default_rng(0)
    pool = rng.integers(0, 2**63, 900).astype(np.uint64)
    a, b, c = pool[:600], pool[200:800], pool[:1]
    out = sketches(np.concatenate([a, b, c]), np.repeat([0, 1, 2], [600, 600, 1]), 3, 400)
    assert (out != _FREE).all()
    assert abs((out[0] == out[1]).mean() - 0.5) < 0.12


def test_components(spark):
    from variety.llm.components import components

    rng = random.Random(1)
    links = [(i, i + 1) for i in range(40)] + [(100, 200 + i) for i in range(50)] + [(rng.randrange(300, 400), rng.randrange(300, 400)) for _ in range(60)]
    links = [(a, b) for a, b in links if a != b]
    want = groups(links, {x for p in links for x in p})
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(links, "u long, v long")).collect()}
    assert got == want


def test_secrets(spark):
    from variety.llm import secrets as S

    rows = [
        (1, 'Password: "abcd1234" and token=ab token = xyz secret=short'),
        (2, "AKIA" + "B" * 12 + " AKIA12 " + "0a" * 16 + " " + "0a" * 15),
        (3, "é日 api_key = 'Zk3vQ9xL2mN8pR4tY7wB' \u212aapi"),
        (4, "Zk3vQ9xL2mN8pR4tY7wBs1 123e4567-e89b-12d3-a456-426614174000 " + "D" * 40),
        *ODD,
    ]
    got = {r["doc_id"]: r for r in S.find_secrets(frame(spark, rows)).collect()}
    assert got[1]["base"] == "assign:0:19" and (got[1]["n_assign"], got[1]["n_access"], got[1]["n_hex"]) == (1, 0, 0)
    assert got[2]["base"] == "access:0:16,hex:24:56"
    assert got[3]["base"] == "assign:3:34" and got[3]["spans"] == got[3]["base"]
    assert got[4]["base"] == "" and got[4]["spans"] == "token:0:22"
    assert all(got[i]["spans"] == "" for i, _ in ODD)


def test_redaction_leaves_the_rest(spark):
    from variety.llm.secrets import redact_secrets

    got = {r["doc_id"]: r["text"] for r in redact_secrets(spark, frame(spark, [(1, "x token=abcdefgh12 y"), (2, "plain"), (3, None)]), "").collect()}
    assert got == {1: "x [SECRET] y", 2: "plain", 3: None}


def test_passages(spark):
    from variety.llm.passages import shared_passages

    rng = random.Random(8)
    shared, fuzzy = prose(rng, 70), prose(rng, 90).split()
    edited = [f"z{i}" if i % 12 == 5 else w for i, w in enumerate(fuzzy)]
    rows = [
        (1, prose(rng, 200) + " " + shared + " " + prose(rng, 30)),
        (2, prose(rng, 20) + " " + shared),
        (3, prose(rng, 50) + " " + " ".join(fuzzy) + " " + prose(rng, 50)),
        (4, " ".join(edited) + " " + prose(rng, 10)),
        (5, prose(rng, 300)),
        (6, " ".join(shared.split()[:30]) + " " + prose(rng, 60)),
        *ODD,
    ]
    got = shared_passages(frame(spark, rows)).collect()
    assert {(r["doc_id"], r["other_id"]) for r in got} == {(2, 1), (4, 3)}
    text = dict(rows)
    for r in got:
        assert r["similarity"] >= 0.8 and r["words"] >= 50
        if r["doc_id"] == 2:
            assert shared in text[2][r["start"] : r["end"]] and shared in text[1][r["other_start"] : r["other_end"]]
    assert shared_passages(frame(spark, [])).count() == 0


def test_several_passages_of_one_pair(spark):
    from variety.llm.passages import shared_passages

    rng = random.Random(18)
    head, foot, long = prose(rng, 60), prose(rng, 60), prose(rng, 110).split()
    rows = [
        (1, f"{head} {prose(rng, 40)} {foot}"),
        (2, f"{head} {prose(rng, 40)} {foot}"),
        (3, " ".join(long)),
        (4, " ".join(long[:55]) + " " + prose(rng, 35) + " " + " ".join(long[55:])),
    ]
    got = shared_passages(frame(spark, rows)).collect()
    text = dict(rows)
    parts = {(r["doc_id"], r["other_id"], text[r["doc_id"]][r["start"] : r["end"]]) for r in got}
    assert parts == {(2, 1, head), (2, 1, foot), (4, 3, " ".join(long[:55])), (4, 3, " ".join(long[55:]))}
    assert all(text[r["other_id"]][r["other_start"] : r["other_end"]] == text[r["doc_id"]][r["start"] : r["end"]] and r["similarity"] == 1 for r in got)


def test_passages_whose_parts_come_first_elsewhere(spark):
    from variety.llm.passages import shared_passages

    rng = random.Random(28)
    halves, lines = prose(rng, 60).split(), prose(rng, 66).split()
    whole, licence = " ".join(halves), " ".join(lines)
    rows = [(1, f"{prose(rng, 40)} {' '.join(halves[:30])} {prose(rng, 9)}"), (2, f"{' '.join(halves[30:])} {prose(rng, 40)}")]
    rows += [(3 + i, f"{prose(rng, 12)} {' '.join(lines[22 * i : 22 * i + 22])} {prose(rng, 30)}") for i in range(3)]
    rows += [(10 + 4 * i, f"{prose(rng, 50)} {whole} {prose(rng, 40)}") for i in range(4)]
    rows += [(11 + 4 * i, f"{prose(rng, 30)} {licence} {prose(rng, 40)}") for i in range(4)]
    rows += [(12 + 4 * i, f"{prose(rng, 20)} {' '.join(halves[:30])} {prose(rng, 40)} {' '.join(lines[22:44])}") for i in range(4)]
    for parts in (1, 12):
        got = shared_passages(frame(spark, rows).repartition(parts)).collect()
        text = dict(rows)
        found = {r["doc_id"] for r in got if any(p in text[r["doc_id"]][r["start"] : r["end"]] for p in (whole, licence))}
        assert found == {i for i, t in rows if i > 11 and (whole in t or licence in t)}


@pytest.mark.parametrize("words", [55, 70])
def test_passages_with_many_edits(spark, words):
    from variety.llm.passages import shared_passages

    rng = random.Random(38)
    rows, number = [], 0
    for step in (5, 6, 7, 8):
        for _ in range(10):
            own = prose(rng, words).split()
            edited = [f"z{number}-{i}" if i % step == step - 1 else w for i, w in enumerate(own)]
            rows += [(number, f"{prose(rng, 40)} {' '.join(own)} {prose(rng, 40)}"), (number + 1, f"{prose(rng, 40)} {' '.join(edited)} {prose(rng, 40)}")]
            number += 2
    got = shared_passages(frame(spark, rows)).collect()
    assert {(r["doc_id"], r["other_id"]) for r in got} == {(i + 1, i) for i in range(0, number, 2)}


def test_passages_of_holders_in_between(spark):
    """All seeds of a passage stand first, and next before, in documents that hold 49 of its words."""
    from variety.llm.passages import shared_passages

    rng = random.Random(38)
    whole = prose(rng, 60).split()
    piece = lambda k: f"{prose(rng, 30)} {' '.join(whole[k : k + 49])} {prose(rng, 30)}"
    starts = (0, 5, 11)
    rows = [(1 + i, piece(k)) for i, k in enumerate(starts)]
    rows += [(10, f"{prose(rng, 50)} {' '.join(whole)} {prose(rng, 20)}")]
    rows += [(11 + i, piece(k)) for i, k in enumerate(starts)]
    rows += [(20, f"{prose(rng, 20)} {' '.join(whole)} {prose(rng, 50)}")]
    for parts in (1, 7):
        got = shared_passages(frame(spark, rows).repartition(parts)).collect()
        text = dict(rows)
        assert {(r["doc_id"], r["other_id"], text[r["doc_id"]][r["start"] : r["end"]]) for r in got} == {(20, 10, " ".join(whole))}


def test_links_of_all_holders():
    from variety.llm.passages import HOLDERS, links

    for n in (2, HOLDERS, HOLDERS + 1):
        doc = np.arange(n) * 3
        row, other = links(np.zeros(n, np.uint64), doc, np.zeros(n, np.int32))
        pairs = set(zip(row.tolist(), other.tolist(), strict=True))
        want = {(i, j) for i in range(n) for j in range(i)} if n <= HOLDERS else {(i, j) for i in range(1, n) for j in (0, i - 1)}
        assert len(row) == len(pairs) and pairs == want


def test_links_of_repeated_seeds():
    from variety.llm.passages import links

    seed = np.array([1, 1, 1, 1, 1, 2, 2, 3], np.uint32)
    doc = np.array([1, 1, 2, 3, 3, 4, 4, 5])
    row, other = links(seed, doc, np.arange(8))
    assert sorted(zip(row.tolist(), other.tolist(), strict=True)) == [(2, 0), (2, 1), (3, 0), (3, 1), (3, 2), (4, 0), (4, 1), (4, 2)]


def test_pieces_are_the_longest():
    from variety.llm.passages import pieces

    rng = np.random.default_rng(4)
    for _ in range(20):
        differ = (rng.random(200) < rng.choice([0.1, 0.25, 0.4])).astype(np.int64)
        got = pieces(np.stack([np.ones(200, np.int64), np.ones(200, np.int64), differ], axis=1))
        fits = [j - i for i in range(200) for j in range(i + 50, 201) if not differ[i] and not differ[j - 1] and 5 * differ[i:j].sum() <= j - i]
        assert max((j - i for i, j in got), default=0) == max(fits, default=0)


def test_chain_is_the_best_chain():
    from variety.llm.passages import chain

    rng = np.random.default_rng(2)
    for _ in range(30):
        n = 7
        a, b, size = rng.integers(0, 40, n), rng.integers(0, 40, n), rng.integers(3, 9, n)

        def score(path, a=a, b=b, size=size):
            total = 0.0
            for x, i in enumerate(path):
                if x:
                    j = path[x - 1]
                    gap = a[i] - a[j] - size[j], b[i] - b[j] - size[j]
                    if min(gap) < 0:
                        return -1.0
                    total -= 0.25 * sum(gap)
                total += size[i]
            return total

        order = sorted(range(n), key=lambda i: (a[i], b[i]))
        best = max(score([order[j] for j in range(n) if mask >> j & 1]) for mask in range(1, 1 << n))
        assert abs(score(chain(a, b, size)) - best) < 1e-9


def test_cutting_keeps_the_first(spark):
    from variety.llm.passages import cut_shared_passages

    rng = random.Random(8)
    shared = prose(rng, 80)
    rows = [(1, "first " + shared), (2, "second " + shared + " end"), (3, "clean text"), (4, None)]
    got = {r["doc_id"]: r["text"] for r in cut_shared_passages(spark, frame(spark, rows), "").collect()}
    assert got[1] == rows[0][1] and shared not in got[2] and got[2].startswith("second") and got[3] == "clean text" and got[4] is None


def test_urls(spark):
    from variety.llm.urls import judged_urls

    rows = [(1, None), (2, "x"), (3, "http://COM/"), (4, "a://www.Example.com/en/x?y"), (5, "h://e.net/es/#"), (6, "://net/fr/1"), (7, "http://aa.example.com/en/"), (7, "http://aa.example.com/en/"), (8, "")]
    got = {r["page_id"]: r for r in judged_urls(spark.createDataFrame(rows, "page_id long, url string")).collect()}
    assert [got[i]["rule"] for i in range(1, 8)] == [None, None, "com/", "www.example.com/en/", "net/es/", "net/fr/", "example.com/en/"]
    assert got[4]["host"] == "www.example.com" and got[4]["path"] == "/en/x" and got[1]["host"] == got[8]["path"] == ""
    assert judged_urls(spark.createDataFrame([], "page_id long, url string")).count() == 0


def test_url_models_against_counts(spark):
    from variety.llm.urls import END, ORDER, PAD, gram_scores

    rng = random.Random(3)
    good, bad = ["".join(rng.choice("abc") for _ in range(6)) for _ in range(20)], ["".join(rng.choice("bcd") for _ in range(6)) for _ in range(20)]
    grams = {}
    for c, urls in (("a", good), ("r", bad)):
        for s in urls:
            p = PAD * (ORDER - 1) + s + END
            for i in range(len(s) + 1):
                grams.setdefault(p[i : i + ORDER], {"a": 0, "r": 0})[c] += 1

    def prob(c, g):
        if not g:
            return 1 / 256
        low = prob(c, g[1:])
        seen = {}
        for x, n in grams.items():
            tail = x[ORDER - len(g) :]
            if tail[:-1] == g[:-1] and n[c]:
                seen[tail[-1]] = seen.get(tail[-1], 0) + n[c]
        total = sum(seen.values())
        return (seen.get(g[-1], 0) + len(seen) * low) / (total + len(seen)) if total else low

    rows = spark.createDataFrame([(g, n["a"], n["r"]) for g, n in grams.items()], "g string, a long, r long")
    got = {r["g"]: r["gain"] for r in gram_scores(rows).collect()}
    for g in list(grams)[:40]:
        assert abs(got[g] - np.log(prob("a", g) / prob("r", g))) < 1e-9


def test_warc_round_trip(spark, tmp_path):
    from variety.llm import warc as W

    rng = random.Random(5)
    big = "<p>" + "é".join(prose(rng, 30) for _ in range(900)) + "</p>"
    rows = [(5, "u", big), (3, "u\r\nX: y", big), (7, None, "<b>" + "x" * 120), (8, "v", "<b>" + "x" * 120), (9, "v", "short"), (10, "v", "short"), (11, "v", None), (12, "v", ""), (8, "v", "<b>" + "x" * 120), (None, "n", "y" * 200), (20, "w", "WARC/1.1\r\n\r\n" * 40)]
    W.write_archives(spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3), str(tmp_path / "a"))
    got = sorted((str(W.page_of(r["record_id"])), r["payload_bytes"], r["payload_digest"], r["type"], r["refers_to"] and W.page_of(r["refers_to"])) for r in W.resolved(W.read_archives(spark, str(tmp_path / "a"))).collect())
    first = {}
    for page, _, html in sorted((r for r in rows if r[0] is not None), key=lambda r: r[0]):
        if html and len(html.encode()) >= 100:
            first.setdefault(html, page)
    want = []
    for page, _, html in rows:
        raw = (html or "").encode()
        lead = first.get(html, page) if len(raw) >= 100 else page
        again = page is not None and lead != page
        want.append((str(page), len(raw), hashlib.sha256(raw).hexdigest(), "revisit" if again else "response", lead if again else None))
    assert got == sorted(want, key=lambda r: (r[0], r[1])) or sorted(got, key=repr) == sorted(want, key=repr)


def test_broken_segments(spark):
    from variety.llm import warc as W

    block = W.HTTP_HEAD + W.chunked(b"x" * 50)
    import pyarrow as pa

    def assemble(parts):
        batch = pa.RecordBatch.from_pylist([{"record_id": "r", "uri": "u", "parts": parts}])
        return [r["payload"] for b in W._assemble(iter([batch])) for r in b.to_pylist()]

    a = {"segment": 1, "total": None, "block": block[:40]}
    b = {"segment": 2, "total": len(block), "block": block[40:]}
    assert assemble([b, a]) == [b"x" * 50]
    assert assemble([b]) == [None] and assemble([a, b | {"total": 1}]) == [None] and assemble([a, b | {"segment": 3}]) == [None]
    assert W.dechunked(b"5\r\nabc") is None and W.dechunked(b"zz\r\n") is None


def test_segmentations_are_distinct_and_exact(spark):
    from variety.llm import segmentations as S

    rows = [(1, "ab cd efg"), (2, "hello world of texts"), *ODD[:6]]
    pieces = S.Pieces(S.vocabulary_path("piece_bpe_32k.model"))
    text = dict(rows)
    got = S.sampled_segmentations(frame(spark, rows), 4).collect()
    for r in got:
        assert pieces.decode(r["ids"]) == text[r["doc_id"]] and zlib.crc32(np.array(r["ids"], "<u4").tobytes()) == r["ids_crc32"]
    for i in {r["doc_id"] for r in got}:
        own = sorted((r for r in got if r["doc_id"] == i), key=lambda r: r["rank"])
        assert len({tuple(r["ids"]) for r in own}) == len(own)
        assert [r["perturbed"] for r in own] == sorted((r["perturbed"] for r in own), reverse=True)
    again = S.sampled_segmentations(frame(spark, rows).repartition(5), 4).collect()
    assert sorted(map(tuple, [(r["doc_id"], r["rank"], r["ids_crc32"]) for r in got])) == sorted((r["doc_id"], r["rank"], r["ids_crc32"]) for r in again)


def test_lattices_fall_apart_only_where_no_piece_is():
    from variety.llm import segmentations as S

    pieces = S.Pieces(S.vocabulary_path("piece_bpe_32k.model"))
    spelt = {x.replace(S.SPACE, " "): v for x, v in pieces.weight.items()}
    text = "x" + " l'été, (foo)bar\n▁▁a12 ##%% 漢字, ﬁn" * 2
    whole = S.Search(S.Lattices(pieces), pa.array([text]), np.zeros(1, np.uint64))
    spaced = " " + text
    mass = [0.0] * (len(spaced) + 1)
    for i in range(len(spaced) - 1, -1, -1):
        ways = [spelt[x][1] + mass[j] for j in range(i + 1, min(len(spaced), i + S.MOST_PIECE) + 1) if (x := spaced[i:j]) in spelt]
        if spaced[i] not in spelt:
            ways.append(pieces.byte_weight * len(spaced[i].encode()) + mass[i + 1])
        mass[i] = float(np.logaddexp.reduce(ways))
    for edges, log_prob, *_ in whole.run(5)[0][:5]:
        ids = [i for c in whole.code[edges].tolist() for i in pieces.ids_of(c)]
        weight = sum(pieces.byte_weight * len(chr(-c - 1).encode()) if c < 0 else dict((v[0], v[1]) for v in spelt.values())[c] for c in whole.code[edges].tolist())
        assert pieces.decode(ids) == text and abs(log_prob - (weight - mass[0])) < 1e-6
    held = S.Lattices(pieces, most=3)
    apart = [S.Search(held, pa.array([t]), np.array([7], np.uint64)).run(2)[0][0][1] for t in ("abc def", "ghi abc def, jk", "abc def")]
    assert apart[0] == apart[2]


def test_segmentation_frequencies():
    from variety.llm import bytescan as B
    from variety.llm import segmentations as S

    pieces = S.Pieces(S.vocabulary_path("piece_bpe_32k.model"), power=0.3)
    n = 6000
    found = S.Search(S.Lattices(pieces), pa.array(["abc"] * n), B.mix64(np.arange(n, dtype=np.uint64))).run(2)
    chance, first, second = {}, {}, {}
    for r in found:
        for x in r[:2]:
            chance[tuple(x[0])] = float(np.exp(x[1]))
        first[tuple(r[0][0])] = first.get(tuple(r[0][0]), 0) + 1
        pair = tuple(r[0][0]), tuple(r[1][0])
        second[pair] = second.get(pair, 0) + 1
    assert abs(sum(chance.values()) - 1) < 1e-6
    for path, c in first.items():
        assert abs(c / n - chance[path]) < 5 * (chance[path] / n) ** 0.5 + 1e-3
    for (a, b), c in second.items():
        p = chance[a] * chance[b] / (1 - chance[a])
        assert abs(c / n - p) < 5 * (p / n) ** 0.5 + 1e-3


def test_packing(spark, texts):
    import public_tokenizers
    from tokenizers import Tokenizer

    from variety.llm.packing import pack

    coder = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    texts = [*texts, *((10_000 + i, t) for i, t in enumerate(["x  ", "abc", "a <|endoftext|> b", "<|endoftext|>", "a  <|endoftext|><|endoftext|>  ", "<|endoftext"]))]
    got = pack(frame(spark, texts)).collect()
    for i, t in texts:
        ids = coder.encode(t or "", add_special_tokens=False).ids + [2]
        own = sorted((r for r in got if r["doc_id"] == i), key=lambda r: r["piece"])
        assert [r["piece"] for r in own] == list(range(len(own))) and sum(r["length"] for r in own) == len(ids)
        for r in own:
            assert r["length"] == 1024 or r["piece"] == 0
            assert r["ids_crc32"] == zlib.crc32(np.array(ids[r["start"] : r["start"] + r["length"]], "<u4").tobytes())
    by = {}
    for r in got:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for places in by.values():
        end = 0
        for offset, length in sorted(places):
            assert offset == end
            end += length
        assert end <= 1024
    assert pack(frame(spark, [])).count() == 0


@pytest.mark.parametrize("rule", ["norm", "dot"])
def test_plans_hold_every_capacity(rule):
    from variety.llm.packing import Capacity, plan

    rng = random.Random(6)
    cap = Capacity(tokens=100, documents=4, attention=3500, rule=rule)
    histogram = {n: rng.randrange(1, 300) for n in rng.sample(range(1, 60), 25)}
    held, placed = {}, {}
    for length, rank, n, first, copies, offset in plan(histogram, cap):
        assert rank == placed.get(length, 0)
        placed[length] = rank + n
        for i in range(n):
            held.setdefault(first + i // copies, []).append((offset + i % copies * length, length))
    assert placed == histogram
    for places in held.values():
        places.sort()
        assert len(places) <= 4 and sum(n for _, n in places) <= 100 and sum(n * n for _, n in places) <= 3500
        assert all(a + n == b for (a, n), (b, _) in zip(places[:-1], places[1:], strict=True))


def test_embeddings(spark):
    from variety.llm.embeddings import near_vectors

    rng = np.random.default_rng(7)
    base = rng.normal(size=(40, 16))
    x = np.concatenate([base, base[:10] + 0.1 * rng.normal(size=(10, 16)), base[:5], base[0] + 0.15 * rng.normal(size=(30, 16))]).astype(np.float32)
    odd = [(900, None), (901, [0.0] * 16), (902, [float("nan")] * 16), (903, [None] * 16), (904, [1.0, 2.0]), (905, [])]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + odd
    got = {r["vec_id"]: r for r in near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect()}
    u = x.astype(float)
    u /= np.linalg.norm(u, axis=1, keepdims=True)
    link = u @ u.T >= 0.9
    np.fill_diagonal(link, False)
    want = groups(list(zip(*np.nonzero(link), strict=True)), range(len(x)))
    assert {i: got[i]["n_links"] for i in range(len(x))} == dict(enumerate(link.sum(axis=1)))
    assert {i: got[i]["component_id"] for i in range(len(x))} == want
    assert all(got[i]["n_links"] == 0 and got[i]["component_id"] == i and got[i]["kept"] for i, _ in odd)
    assert near_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


@pytest.mark.parametrize("block", [2048, 70])
def test_embeddings_of_few_directions(spark, monkeypatch, block):
    from variety.llm import embeddings
    from variety.llm.embeddings import near_vectors

    monkeypatch.setattr(embeddings, "BLOCK_ROWS", block)
    rng = np.random.default_rng(17)
    x = rng.normal(size=(1200, 4)) @ np.linalg.qr(rng.normal(size=(256, 4)))[0].T
    got = {r["vec_id"]: r["n_links"] for r in near_vectors(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")).collect()}
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    link = u @ u.T >= 0.9
    np.fill_diagonal(link, False)
    assert got == dict(enumerate(link.sum(axis=1).tolist()))


def test_fingerprints(spark):
    from variety.llm.order_minhash import fingerprints

    rng = random.Random(9)
    rows = [(i * 3, prose(rng, rng.choice([3, 60, 200]))) for i in range(30)] + [(500, prose(rng, 60)), (501, None), (502, ""), (503, "a b a b a b a b a b")]
    rows.append((600, rows[4][1]))
    rng.shuffle(rows)
    got = {r["doc_id"]: r for r in fingerprints(frame(spark, rows)).collect()}
    order = sorted(rows)
    for n, (i, t) in enumerate(order):
        t, after = t or "", order[(n + 1) % len(order)][1] or ""
        half = len(t) // 2
        assert got[i]["edited"] == t[: len(t) - half] + after[:half] and got[i]["n_chars"] == len(t)
        assert 0 <= got[i]["near_edited"] <= 1 and 0 <= got[i]["near_next"] <= 1
    assert got[600]["fingerprint"] == got[12]["fingerprint"]
    long = [r for r in got.values() if r["n_chars"] > 300]
    assert np.mean([r["near_edited"] for r in long]) > 0.05 > np.mean([r["near_next"] for r in long])
    assert fingerprints(frame(spark, [])).count() == 0


def test_occurrence_numbers_and_order(spark):
    """The fingerprint against a plain version of its definition."""
    from variety.llm.order_minhash import BINS, K, PICKED, PLACE_BITS, with_fingerprint

    texts = ["a b c a b c a b c", "x " * 30, "one two three four five six seven", ""]
    rows = spark.createDataFrame([(t,) for t in texts], "text string")
    got = [r["f"] for r in with_fingerprint(rows, "text", "f").collect()]

    def hashed(*args):
        return spark.range(1).select(F.xxhash64(*args)).first()[0]

    mask = (1 << PLACE_BITS) - 1
    for t, f in zip(texts, got, strict=True):
        w = t.split(" ")
        seen, items = {}, []
        for i in range(max(len(w) - K, 0) + 1):
            h = hashed(*(F.lit(w[i + j] if i + j < len(w) else None).cast("string") for j in range(K))) & ~mask
            n = seen[h] = seen.get(h, -1) + 1
            items.append(((hashed(F.lit(h >> PLACE_BITS).cast("long"), F.lit(n)) & ~mask if n else h) | i))
        bins = {}
        for x in sorted(items):
            bins.setdefault((x % (1 << 64)) >> (64 - (BINS - 1).bit_length()), []).append(x)
        want = ["." * 8] * BINS
        for b, xs in bins.items():
            ordered = [x >> PLACE_BITS for x in sorted(xs[:PICKED], key=lambda x: x & mask)]
            want[b] = f"{hashed(F.array(*(F.lit(x).cast('long') for x in ordered))) % (1 << 64):016X}"[8:]
        assert f == "".join(want)


def test_toxicity_held_out(spark):
    from variety.llm.toxicity import drop_toxic, fit_toxicity, learnable, toxicity

    rng = random.Random(2)
    rows, labels = [], []
    for i in range(600):
        bad = i % 4 == 0
        w = prose(rng, 40).split()
        if bad:
            w[rng.randrange(40)] = rng.choice(["nastyword", "vileish", "vilely"])
        rows.append((i, " ".join(w)))
        labels.append((i, 1, int(bad)))
    docs, marks = frame(spark, rows + ODD), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r["score"] for r in toxicity(docs, learnable(marks)).collect()}
    held = [(i, t) for i, _, t in labels if zlib.crc32(str(i).encode()) % 3 == 1]
    assert np.mean([(got[i] >= 0.7) == bool(t) for i, t in held]) > 0.97
    assert len(got) == len(rows) + len(ODD) and all(0 <= s <= 1 for s in got.values()) and max(got[i] for i, _ in ODD) < 0.7
    buckets, values, _ = fit_toxicity(docs, marks.where("toxic = 1"))
    assert not len(buckets) and toxicity(frame(spark, []), marks).count() == 0
    assert drop_toxic.__doc__


def test_cells_that_take_turns_lose_no_link_and_write_less_at_once(spark, monkeypatch):
    from variety.llm import embeddings as E

    rng = np.random.default_rng(8)
    x = rng.normal(size=(400, 6)).astype(np.float32)
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>").cache()
    plain, most = E.written, []

    def seen(df, name):
        back = plain(df, name)
        if name == "placed":
            most.append(back.count())
        return back

    monkeypatch.setattr(E, "written", seen)
    at_once = sorted(map(tuple, E.near_vectors(rows).collect()))
    every = most.pop()
    monkeypatch.setattr(E, "TURN_BYTES", 20_000, raising=False)
    assert sorted(map(tuple, E.near_vectors(rows).collect())) == at_once
    assert len(most) > 2 and max(most) < every / 2 and sum(most) == every
    assert sum(r[1] for r in at_once) > 100


def test_the_segmentations_themselves_are_rows_of_the_query(spark, small):
    import zlib

    from variety.llm.queries import QUERIES

    rows = QUERIES["op6_sampled_segmentations"](spark, small).limit(20).collect()
    assert rows and all(len(r["ids"]) == r["n_pieces"] and zlib.crc32(np.array(r["ids"], "<u4").tobytes()) == r["ids_crc32"] for r in rows)


def test_no_short_seed_is_left_out():
    from variety.llm import passages as P

    raw = np.frombuffer(b" ".join(b"w%d" % i for i in range(200)), np.uint8)
    words, _, _, rows = P.row_words(raw, np.array([0, len(raw)]))
    seeds, at = next(iter(P.selected(words, rows, P.long_mark(8))))
    assert at.tolist() == list(range(200 - P.SEED_WORDS + 1)) and len(set(seeds.tolist())) == len(at)


def test_seeds_and_matches_travel_in_small_batches():
    import tracemalloc

    from variety.llm import passages as P

    rng = np.random.default_rng(5)
    words = np.array([f"w{i:05d}" for i in range(50_000)])
    texts = [" ".join(rng.choice(words, 3000)) for _ in range(430)]
    batches = [pa.RecordBatch.from_arrays([pa.array(np.arange(i, i + 43)), pa.array(texts[i : i + 43])], ["doc_id", "text"]) for i in range(0, 430, 43)]
    tracemalloc.start()
    sizes = [b.nbytes for b in P._seeds(9)(iter(batches))]
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert sum(sizes) > 16 * 430 * 2990 and max(sizes) < 4 << 20
    assert most < 100 << 20  # 144 MB when a flush kept all it had made
    texts = pa.array([" ".join(f"{k}v{i}" for i in range(4000)) for k in range(8)] * 40)
    packed = [b for i in range(0, 320, 80) for b in P._seeds(9)(iter([pa.RecordBatch.from_arrays([pa.array(np.arange(i, i + 80)), texts.slice(i, 80)], ["doc_id", "text"])]))]
    table = pa.Table.from_batches(packed).sort_by("bucket")
    assert max(b.nbytes for b in P._refer(9)(iter(table.to_batches()))) < 4 << 20
    assert [P.bucket_tasks(n << 20, 51) for n in (0, 204, 512, 1 << 40)] == [[], [], [128], [204]]
