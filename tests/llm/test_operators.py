"""Every operator against brute force, on the smallest tables and on odd rows."""

import hashlib
import re
import struct
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from keyless.llm import bpe, dedup, entry, jaccard, kernels, licenses, packing, quality, resharding, suffixes, tokenfiles, vafile, vocab, warc
from tests.llm.conftest import rows_of

Q = entry.queries()
WORD = re.compile("[^\x20\x09-\x0d]+")


def name(n):
    return next(k for k in Q if k.startswith(f"op{n}_"))


def got(spark, n, folder):
    return [r.asDict() for r in Q[name(n)](spark, folder).collect()]


def both(sf, edge):
    return [sf, edge]


@pytest.mark.parametrize("n", range(1, 11))
def test_empty_tables(spark, nothing, n):
    assert got(spark, n, nothing) == []


def slow_removed(texts, length=200):
    data = [(t or "").encode() for t in texts]
    seen = Counter(d[i : i + length] for d in data for i in range(len(d) - length + 1))
    out = []
    for d in data:
        under = bytearray(len(d))
        for i in range(len(d) - length + 1):
            if seen[d[i : i + length]] > 1:
                under[i : i + length] = b"\1" * length
        spans = [m.span() for m in re.finditer(b"\1+", bytes(under))]
        kept = bytes(b for b, u in zip(d, under) if not u)
        out.append((len(d), len(d) - len(kept), len(spans), hashlib.sha256(kept).hexdigest()))
    return out


@pytest.mark.parametrize("which", ["sf", "edge"])
def test_dedup(spark, request, which):
    folder = request.getfixturevalue(which)
    rows = [(d, t if t is None or len(t) < 100_000 else t[:3000]) for d, t in rows_of(spark, folder)] if which == "edge" else rows_of(spark, folder)
    if which == "edge":
        import tempfile

        folder = tempfile.mkdtemp()
        spark.createDataFrame(rows, "doc_id long, text string").repartition(3).write.parquet(f"{folder}/documents.parquet")
    want = Counter((d, *x) for (d, _), x in zip(rows, slow_removed([t for _, t in rows])))
    have = Counter((r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got(spark, 1, folder))
    assert have == want


def test_dedup_passages_with_many_borders(spark, tmp_path):
    rng = np.random.default_rng(5)
    word = lambda k: "".join(chr(97 + x) for x in rng.integers(0, 4, k))
    passages = [word(int(rng.integers(150, 420))) for _ in range(12)]
    docs = []
    for i in range(150):
        text = ""
        for _ in range(int(rng.integers(1, 5))):
            p = passages[int(rng.integers(0, 12))]
            a = int(rng.integers(0, 80))
            text += word(int(rng.integers(0, 60))) + p[a : len(p) - int(rng.integers(0, 80))]
        docs.append((i, text))
    spark.createDataFrame(docs, "doc_id long, text string").repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    rows = rows_of(spark, str(tmp_path))
    want = Counter((d, *x) for (d, _), x in zip(rows, slow_removed([t for _, t in rows])))
    assert Counter((r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got(spark, 1, str(tmp_path))) == want


def test_dedup_text_keeps_whole_characters(spark, edge):
    out = dedup.drop_repeats(spark.read.parquet(f"{edge}/documents.parquet")).collect()
    assert all("�" not in r["kept_text"] for r in out)
    assert {r["row"] for r in out} == {"row"}


def test_loser_tree_orders_and_never_compares_known_prefixes():
    rng = np.random.default_rng(1)
    runs = [sorted({bytes(rng.integers(97, 99, 12).astype(np.uint8)) for _ in range(n)}) for n in (50, 1, 200, 0, 77)]
    coded = [suffixes.front_code(r, 12) for r in runs if r]
    tree = suffixes.LoserTree([suffixes.decode(s, t, 12) for s, t in coded], 12)
    full, out, last = [r for r in runs if r], [], b""
    while (x := tree.next()) is not None:
        s = full[x[1]][x[2]]
        if out:
            share = next((i for i in range(12) if s[i] != last[i]), 12)
            assert share == x[0]
        out.append(s)
        last = s
    assert out == sorted(s for r in runs for s in r)
    assert tree.compared < len(out) * 3


@pytest.mark.parametrize("which", ["sf", "odd"])
def test_warc(spark, request, which, tmp_path):
    if which == "odd":
        folder = str(tmp_path)
        rows = [(1, "http://a/ b", None), (2, None, ""), (3, "u", "é" * 100_000), (4, "u", "é" * 100_000), (4, "u", "é" * 100_000), (None, "u", "z"), (5, "u", "z"), (None, None, "alone"), (6, "x\r\ny", "a\r\n\r\nb")]
        spark.createDataFrame(rows, "page_id long, url string, html string").repartition(2).write.parquet(f"{folder}/pages.parquet")
    else:
        folder = request.getfixturevalue("sf")
    rows = [(r[0], (r[1] or "").encode()) for r in spark.read.parquet(f"{folder}/pages.parquet").select("page_id", "html").collect()]
    top = {}
    for p, d in rows:
        if p is not None:
            top[d] = max(top.get(d, p), p)
    want = Counter()
    for p, d in rows:
        lead = top.get(d)
        again = lead is not None and (p is None or p < lead)
        want[p, len(d), warc.base32(hashlib.sha1(d).digest()), "revisit" if again else "response", lead if again else None] += 1
    assert Counter(tuple(r.values()) for r in got(spark, 2, folder)) == want


def test_warc_chunk_table(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    out = defaultdict(list)
    for r in warc.chunk_table(pages, 1000).collect():
        out[r["record"], r["page_id"]].append(r)
    html = {r["page_id"]: (r["html"] or "").encode() for r in pages.collect()}
    for (_, page), rows in out.items():
        rows.sort(key=lambda r: r["chunk_no"])
        assert b"".join(bytes(r["data"]) for r in rows) == html[page]
        assert rows[-1]["digest"] == warc.base32(hashlib.sha1(html[page]).digest()) and rows[-1]["last"]


@pytest.mark.parametrize("which", ["sf", "edge"])
def test_bpe(spark, request, which):
    folder = request.getfixturevalue(which)
    e = vocab.rank_encoder(vocab.default_path(vocab.RANKS), vocab.default_pattern())
    want = Counter()
    for d, t in rows_of(spark, folder):
        ids = e.encode_ordinary(t or "")
        want[d, len(ids), hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()] += 1
    assert Counter((r["doc_id"], r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) for r in got(spark, 3, folder)) == want


def test_bpe_stitches_everywhere():
    pattern = vocab.default_pattern()
    e = vocab.rank_encoder(vocab.default_path(vocab.RANKS), pattern)
    rng = np.random.default_rng(2)
    alphabet = list("ab '\n\t 1!é中") + ["'s", "n't", "   ", "aaaaaaaaaaaa"]
    for _ in range(300):
        text = "".join(alphabet[i] for i in rng.integers(0, len(alphabet), int(rng.integers(0, 400))))
        assert bpe.encode(text, e, pattern, chunk=40, overlap=15) == e.encode_ordinary(text)
    assert bpe.encode("x" * 500, e, pattern, 40, 15) == e.encode_ordinary("x" * 500)
    assert len(bpe.stitch("ab cd " * 100, pattern, 40, 15)) > 10


def slow_links(rows, width, percent):
    sets = []
    for _, t in rows:
        w = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets.append({tuple(w[i : i + width]) for i in range(len(w) - width + 1)} if len(w) >= width else ({tuple(w)} if w else set()))
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                root[find(i)] = find(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            least[find(i)] = min(d, least.get(find(i), d))
    return Counter((d, len(s), least.get(find(i)) if s else d) for i, ((d, _), s) in enumerate(zip(rows, sets)))


@pytest.mark.parametrize("which", ["sf", "edge", "chain"])
def test_jaccard(spark, request, which, tmp_path):
    if which == "chain":
        rng = np.random.default_rng(3)
        docs, n = [], 0
        for base in range(6):
            words = [f"b{base}w{x}" for x in range(60)]
            for _ in range(25):
                w = list(words)
                for k in rng.integers(0, 60, int(rng.integers(0, 4))):
                    w[k] = f"n{n}x{k}"
                docs.append((n, " ".join(w)))
                n += 1
        folder = str(tmp_path)
        spark.createDataFrame(docs, "doc_id long, text string").repartition(3).write.parquet(f"{folder}/documents.parquet")
    else:
        folder = request.getfixturevalue(which)
    rows = rows_of(spark, folder)
    assert Counter((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got(spark, 4, folder)) == slow_links(rows, 4, 85)


def test_jaccard_prefixes_hold_enough_matches():
    n = np.arange(0, 300)
    at = np.concatenate([[0], np.cumsum(n)])
    m, size = jaccard.choose(n, at, np.zeros(at[-1]), 85)
    assert (size <= n).all() and (m[1:] >= 1).all()
    m, size = jaccard.choose(n, at, np.full(at[-1], 1e6), 85)
    assert (m > 1).any()


def test_kernels_words_and_shingles_ignore_neighbours():
    texts = ["a b c d e", "", "a b c d e", "A B C D E"]
    raw = "".join(texts).encode()
    offs = np.cumsum([0, *[len(t) for t in texts]])
    h, at = kernels.shingles(np.frombuffer(raw, np.uint8), offs, 4)
    sets = [set(h[a:b].tolist()) for a, b in zip(at[:-1], at[1:])]
    assert sets[0] == sets[2] == sets[3] and len(sets[0]) == 2 and not sets[1]


@pytest.mark.parametrize("which", ["sf", "edge"])
def test_licenses_base(spark, request, which):
    folder = request.getfixturevalue(which)
    want = Counter()
    for d, t in rows_of(spark, folder):
        w = re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        at = [(i, label) for p, label in licenses.BASE for i in range(len(w)) if w[i : i + len(p.split())] == p.split()]
        want[d, len(w), len(at), min((i for i, _ in at), default=None), max((i for i, _ in at), default=None), ",".join(sorted({x for _, x in at}))] += 1
    have = got(spark, 5, folder)
    assert Counter((r["doc_id"], r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) for r in have) == want
    assert all(0 <= r["score"] <= 1 and set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(",")) for r in have)


def slow_scan(text):
    """The rules one after another, in plain Python."""
    w = re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", re.sub("[A-Z]", lambda m: m[0].lower(), text))
    norm = " " + " ".join(w) + " "
    found = []
    for order, (label, rank, key, body) in enumerate(licenses.rules()):
        for m in re.finditer(f" (?:{body})(?= )", norm):
            assert set(key.split("|")) & set(m[0].split()), (key, m[0])
            found.append((norm[: m.start()].count(" "), -m[0].count(" "), rank, order, label))
    kept, end, top = [], -1, 0
    for start, minus, rank, order, label in sorted(found):
        inside = start - minus <= end
        if not inside or rank < top:
            kept.append(label)
        top = top if inside else rank
        end = max(end, start - minus)
    return ",".join(sorted(set(kept) | {label for p, label in licenses.BASE if f" {p} " in norm}))


def test_licenses_rules(spark, edge):
    texts = [
        "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License.", "SPDX-License-Identifier: MIT", "This work is CC BY-SA 4.0",
        "GNU Lesser General Public License version 2.1 or later", "Copyright (c) 2019 2020 Someone. All rights reserved.", "nothing to see here", "Redistribution and use in source and binary forms, with or without modification, are permitted",
        "http://creativecommons.org/licenses/by-nc/3.0/ cc by cc by cc by", "GPLv3 gpl v2 gpl3 agplv3 mpl 2.0 beerware license psf license unauthorised copying prohibited for noncommercial use trademarks of", "released into the public domain; do what the fsck you want to public license",
    ]
    out = licenses.scan(spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")).orderBy("doc_id").collect()
    assert [r["labels"] for r in out] == [slow_scan(t) for t in texts]
    assert out[5]["score"] == 0 and out[1]["score"] == 1
    assert out[1]["labels"] == "mit" and "apache-2.0" in out[0]["labels"] and out[5]["labels"] == "" and "cc-by-sa-4.0" in out[2]["labels"]
    assert len(licenses.rules()) > 200
    kept = licenses.scan(spark.read.parquet(f"{edge}/documents.parquet"))
    assert kept.columns.count("score") == 1


def token_ids(t):
    from tokenizers import Tokenizer

    if not hasattr(token_ids, "t"):
        token_ids.t = Tokenizer.from_file(vocab.default_path(vocab.VOCAB))
    return token_ids.t.encode(t or "", add_special_tokens=False).ids + [2]


@pytest.mark.parametrize("which", ["sf", "edge"])
def test_packing(spark, request, which):
    folder = request.getfixturevalue(which)
    want = Counter()
    for d, t in rows_of(spark, folder):
        ids = token_ids(t)
        first = len(ids) % 1024 or 1024
        for k, a in enumerate([0, *range(first, len(ids), 1024)]):
            x = ids[a : first if k == 0 else a + 1024]
            want[d, k, a, len(x), zlib.crc32(struct.pack(f"<{len(x)}I", *x))] += 1
    have = got(spark, 6, folder)
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in have) == want
    sequences = defaultdict(list)
    for r in have:
        sequences[r["sequence_id"]].append((r["offset"], r["length"]))
    for parts in sequences.values():
        parts.sort()
        assert parts[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(parts, parts[1:])) and sum(n for _, n in parts) <= 1024
    assert len(sequences) <= 1.03 * -(-sum(r["length"] for r in have) // 1024) + 2


def test_packing_plan_uses_the_histogram():
    rng = np.random.default_rng(4)
    h = Counter(rng.integers(1, 65, 5000).tolist())
    plan = packing.plan(dict(h), 64)
    used = Counter()
    for p, n in plan.items():
        assert sum(p) <= 64
        for x in p:
            used[x] += n
    assert used == h
    assert sum(plan.values()) <= 1.02 * sum(k * v for k, v in h.items()) / 64 + 1


def test_vectors(spark, sf, tmp_path):
    odd = [(0, [1.0, 2.0, 3.0]), (50, [0.5, -1.0]), (50, [0.5, -1.0]), (1, None), (2, [1.0, None, 2.0]), (3, [float("nan"), 1.0, 1.0]), (4, [1.0, 2.0, 3.0]), (5, [1.0, 2.0, 3.0]), (None, [9.0, 9.0, 9.0]), (6, []), (7, [-4.0, 1.0, 2.5])]
    spark.createDataFrame(odd, "vec_id long, embedding array<float>").repartition(2).write.parquet(f"{tmp_path}/embeddings.parquet")
    for folder in (sf, str(tmp_path)):
        rows = [(r[0], r[1]) for r in spark.read.parquet(f"{folder}/embeddings.parquet").select("vec_id", "embedding").collect()]
        whole = [(i, np.floor(256 * np.array(v, float))) for i, v in rows if i is not None and v is not None and None not in v and np.isfinite(np.array(v, float)).all()]
        want = Counter()
        for q, x in {i: x for i, x in whole if i % 50 == 0}.items():
            scores = sorted((-int(sum(a * b for a, b in zip(x, y))), i) for i, y in whole if i != q)[:5]
            for rank, (s, i) in enumerate(scores, 1):
                want[q, rank, i, -s] += 1
        assert Counter(tuple(r.values()) for r in got(spark, 7, folder)) == want


@pytest.mark.parametrize("which", ["sf", "edge"])
def test_token_files(spark, request, which):
    folder = request.getfixturevalue(which)
    rows = rows_of(spark, folder)
    have = sorted(got(spark, 8, folder), key=lambda r: r["start"])
    assert [r["doc_id"] is not None and r["doc_id"] for r in have] == sorted((d is not None and d for d, _ in rows), key=lambda d: -1 if d is False else d)
    at = 0
    for r in have:
        assert r["start"] == at
        at += r["n_tokens"]
    want = Counter((d, len(x := token_ids(t)), zlib.crc32(struct.pack(f"<{len(x)}I", *x))) for d, t in rows)
    assert Counter((r["doc_id"], r["n_tokens"], r["ids_crc32"]) for r in have) == want


def test_pieces_are_the_library(spark):
    e = vocab.piece_encoder(vocab.default_path(vocab.VOCAB))
    rng = np.random.default_rng(6)
    alphabet = list("ab '\n\t    \x1c\x85s1!é中​﻿\x00\r　") + ["'s", "don't", " <|endoftext|>"]
    for _ in range(3000):
        text = "".join(alphabet[i] for i in rng.integers(0, len(alphabet), int(rng.integers(0, 14))))
        assert np.frombuffer(e.encode([text])[0], e.dtype).tolist() == token_ids(text)[:-1]


@pytest.mark.parametrize("which", ["sf", "edge"])
def test_resharding(spark, request, which):
    folder = request.getfixturevalue(which)
    rows = rows_of(spark, folder)
    have = got(spark, 9, folder)
    assert Counter((r["doc_id"], r["size"], r["text_crc32"]) for r in have) == Counter((d, len((t or "").encode()) + 16, zlib.crc32((t or "").encode())) for d, t in rows)
    shards = defaultdict(list)
    for r in have:
        shards[r["shard"]].append((r["slot"], r["size"]))
    assert all(sorted(s for s, _ in x) == list(range(len(x))) for x in shards.values()) and set(shards) <= set(range(40))
    total, most = sum(r["size"] for r in have), max(r["size"] for r in have)
    assert all(abs(sum(z for _, z in shards[j]) - total / 40) <= 4 * most for j in range(40))


def test_shards_by_brute_force(spark, sf):
    from pyspark.sql import functions as F

    raw = F.encode(F.coalesce("text", F.lit("")), "UTF-8")
    line = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", F.pmod(F.xxhash64("doc_id"), F.lit(resharding.OLD)).alias("old"), F.crc32(raw).alias("crc"), (F.octet_length(raw).cast("long") + 16).alias("size"))
    lines = defaultdict(list)
    for r in line.withColumn("block", F.pmod(F.xxhash64(F.col("doc_id"), F.col("crc"), F.lit(7)), F.lit(resharding.BLOCKS))).collect():
        lines[r["old"]].append((r["block"], r["doc_id"], r["crc"], r["size"]))
    old = [sum(x[3] for x in lines[s]) for s in range(max(lines) + 1)]
    flow = resharding.cheapest_transfers(old, resharding.equal_shares(sum(old), 40))
    want, moved = {}, 0
    for s, docs in lines.items():
        ends, at = [], 0
        for j in sorted((j for i, j in flow if i == s), key=lambda j: (j != s, j)):
            at += flow[s, j]
            ends.append((at, j))
        at = 0
        for _, d, _, size in sorted(docs):
            want[d] = next(j for end, j in ends if at < end)
            moved += size * (want[d] != s)
            at += size
    have = got(spark, 9, sf)
    assert {r["doc_id"]: r["shard"] for r in have} == want
    least, most = sum(v for (i, j), v in flow.items() if i != j), max(r["size"] for r in have)
    assert abs(moved - least) <= most * len(flow)


def test_flow_moves_the_fewest_bytes():
    old, room = [100, 0, 50, 30], [60, 60, 60]
    flow = resharding.cheapest_transfers(old, room)
    assert [sum(v for (i, _), v in flow.items() if i == s) for s in range(4)] == old
    assert [sum(v for (_, j), v in flow.items() if j == s) for s in range(3)] == room
    assert sum(v for (i, j), v in flow.items() if i != j) == 180 - (60 + 0 + 50)


def test_rewrite_only_affected_shards(spark, edge, tmp_path):
    from pyspark.sql import functions as F

    placed = resharding.reshard(spark.read.parquet(f"{edge}/documents.parquet"), F.lit(0), shards=3)
    assert placed.columns.count("size") == 1
    back = resharding.rewrite(placed, str(tmp_path / "out"))
    assert back.count() == placed.count()


def slow_quality(t, limits=quality.Limits()):
    t = t or ""
    w = WORD.findall(t)
    tri = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    again = {j for i in range(len(w) - 2) if tri[tuple(w[i : i + 3])] > 1 for j in (i, i + 1, i + 2)}
    seen, dup = set(), 0
    for line in t.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    base = len(w) < 50 or 100 * len(again) > 50 * len(w)
    return len(w), sum(map(len, w)), sum(t.count(c) for c in "#*$%&|<>"), dup, len(again), base


def slow_repeats(t, least):
    w = WORD.findall(t or "")
    order = sorted(range(len(w)), key=lambda i: w[i:])
    under, longest = set(), 0
    for a, b in zip(order, order[1:]):
        n = next((k for k in range(len(w)) if max(a, b) + k >= len(w) or w[a + k] != w[b + k]), 0)
        longest = max(longest, n if n >= 3 else 0)
        if n >= least:
            under |= set(range(a, a + n)) | set(range(b, b + n))
    return len(under), longest


@pytest.mark.parametrize("which", ["sf", "edge"])
def test_quality(spark, request, which):
    folder = request.getfixturevalue(which)
    rows = rows_of(spark, folder)
    have = got(spark, 10, folder)
    assert Counter((r["doc_id"], r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"], r["base_failed"]) for r in have) == Counter((d, *slow_quality(t)) for d, t in rows)
    assert not any(r["kept"] and r["base_failed"] for r in have)
    want = Counter((d, *slow_repeats(t, 8)) for d, t in rows if len(t or "") < 6000)
    size = Counter(d for d, t in rows if len(t or "") >= 6000)
    assert Counter((r["doc_id"], r["covered_words"], r["longest_repeat"]) for r in have if r["doc_id"] not in size) == Counter({k: v for k, v in want.items() if k[0] not in size})


def test_quality_keeps_columns(spark, edge):
    docs = spark.read.parquet(f"{edge}/documents.parquet")
    assert quality.keep_clean(docs).columns == docs.columns
    assert quality.keep_clean(docs).filter("n_words != 1").count() == 0


def test_parity_bitmaps_never_exceed_the_distance_of_sets():
    import numpy as np

    from keyless.llm import jaccard

    rng = np.random.default_rng(3)
    for size in (1, 7, 150, 4000):
        base = rng.integers(0, 2**63, size, dtype=np.uint64)
        other = np.concatenate([base[size // 4 :], rng.integers(0, 2**63, size // 3, dtype=np.uint64)])
        a, b = jaccard.parities(np.concatenate([base, other]), np.array([0, size, size + len(other)])).view(np.uint64)
        assert np.bitwise_count(a ^ b).sum() <= len(np.setxor1d(base, other))
