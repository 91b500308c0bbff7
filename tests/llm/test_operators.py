"""Each operator on a small fixture with nulls, empty and long texts, ties, repeats, empty tables
and columns with clashing names, against a brute-force version."""

import gzip
import hashlib
import json
import math
import re
import zlib
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from patchspace.llm import annuli, chosen_path, media, mixing, packing, quality, sstable, template, token_shards, warc
from patchspace.llm.tokens import default_tokenizer, encoder
from patchspace.shared import new_path

DOCS = "doc_id long, text string, lang string, source string, n_chars long, ids string, block long, length int"
LONG = " ".join(f"word{i % 97} the, quick." for i in range(9000))


def documents(spark, rows=None):
    if rows is None:
        rng = np.random.default_rng(1)
        vocab = [f"w{i}" for i in range(300)]
        rows = [(i, " ".join(rng.choice(vocab, rng.integers(1, 80))), f"s{i % 3}" if i % 7 else "s0") for i in range(60)]
        rows += [(100, None, "s1"), (101, "", None), (102, " \n\t ", "s2"), (103, LONG, "s1"), (None, "no id here at all", "s1"), (5, rows[5][1], "s0"), (104, "Don't <|endoftext|> \x01 é x", None)]
    return spark.createDataFrame([(i, t, "en", s, 0, "x", 1, 2) for i, t, s in rows], DOCS).repartition(4), rows


def token_ids(text, end):
    tok = Tokenizer.from_file(default_tokenizer())
    return np.array(tok.encode(text or "", add_special_tokens=False).ids + [end], "<u4")


def key(rows):
    return sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, str(r[1:])))


# op10


def test_token_shards_equal_the_library_and_support_lookup(spark):
    df, rows = documents(spark)
    manifest = token_shards.write_shards(df, new_path(spark, "test-shards"), block_bytes=2048)
    got = token_shards.read_shards(manifest).collect()
    want = defaultdict(list)
    for i, t, _ in rows:
        want[i].append(token_ids(t, 1).tobytes())
    have = defaultdict(list)
    start = 0
    for r in sorted(got, key=lambda r: r.start):
        assert r.start == start and r.ids_crc32 == zlib.crc32(r.ids)
        start += r.n_tokens
        have[r.doc_id].append(bytes(r.ids))
    assert {k: sorted(v) for k, v in have.items()} == {k: sorted(v) for k, v in want.items()}
    order = [r.doc_id for r in sorted(got, key=lambda r: r.start)]
    assert order[0] is None and order[1:] == sorted(order[1:])
    wanted = spark.createDataFrame([(5,), (103,), (999,), (None,)], "doc_id long")
    found = token_shards.lookup(manifest, wanted).groupBy("doc_id").count().collect()
    assert {r.doc_id: r["count"] for r in found} == {5: 2, 103: 1, None: 1}


def test_token_shards_of_an_empty_table(spark):
    df, _ = documents(spark, [])
    assert token_shards.read_shards(token_shards.write_shards(df, new_path(spark, "test-shards"))).count() == 0


def test_sstable_format(tmp_path):
    path = tmp_path / "x.sst"
    keys = [None, -5, -1, 0, 3, 3, 70_000]
    with path.open("wb") as f:
        w = sstable.Writer(f, block_bytes=16)
        for i, k in enumerate(keys):
            w.add(sstable.encode_key(k), np.array([i, 70_000 * (i % 2)], np.uint32))
        w.finish()
        with pytest.raises(ValueError):
            w.add(sstable.encode_key(0), np.empty(0, np.uint32))
    import pyarrow as pa

    r = sstable.Reader(pa.OSFile(str(path)))
    assert [k for k, _ in r.scan()] == keys
    assert [v[0] for v in r.get_all(3)] == [4, 5] and r.get(7) is None and r.get(-5)[0] == 1
    damaged = bytearray(path.read_bytes())
    damaged[12] ^= 255
    with pytest.raises(Exception):
        list(sstable.Reader(pa.BufferReader(bytes(damaged))).scan())


def test_encoder_equals_the_library_on_odd_texts():
    tok, enc = Tokenizer.from_file(default_tokenizer()), encoder(default_tokenizer())
    import pyarrow as pa

    texts = ["", None, "a,b. c, d. É. x,. 12,", "A\x01b \x01", "İ ̈x don't 'S", "<|startoftext|>Hi,", "ß. ﬁ, ½.", "a b", LONG]
    ids, at = enc.batch(pa.array(["pad"] + texts).slice(1))
    for i, t in enumerate(texts):
        assert list(ids[at[i] : at[i + 1]]) == tok.encode(t or "", add_special_tokens=False).ids


# op8


def check_packing(rows, got, capacity=4096):
    want = defaultdict(list)
    for i, t, _ in rows:
        want[i].append(token_ids(t, 2))
    used = defaultdict(int)
    for r in got:
        assert any(len(w) == r.doc_tokens and zlib.crc32(w[r.start : r.start + r.length].tobytes()) == r.ids_crc32 for w in want[r.doc_id])
        used[r.doc_id] += r.length
    assert used == {i: sum(map(len, w)) for i, w in want.items()}
    by = defaultdict(list)
    for r in got:
        by[r.sequence_id].append(r)
    for s in by.values():
        s.sort(key=lambda r: r.offset)
        at = 0
        for r in s:
            assert r.offset == at
            at += r.length
        assert at <= capacity and all(r.sequence_tokens == at for r in s)
    return by


@pytest.mark.parametrize("fan,parts", [(32, 4), (2, 7)])
def test_packing_covers_every_token_once(spark, fan, parts):
    df, rows = documents(spark)
    got = packing.pack(df.repartition(parts), fan=fan, open_windows=3).collect()
    by = check_packing(rows, got)
    assert sum(s[0].sequence_tokens < 4096 - 32 for s in by.values()) <= 1


def test_packing_edge_tables(spark):
    df, _ = documents(spark, [])
    assert packing.pack(df).count() == 0
    df, rows = documents(spark, [(1, None, "a")])
    (r,) = packing.pack(df).collect()
    assert (r.doc_id, r.length, r.doc_tokens, r.padded_length) == (1, 1, 1, 1)


# op1


def test_mixing_weights_and_streams(spark):
    rows = [(i, "w " * (1 + i % 5), "big" if i < 160 else "small" if i < 195 else None) for i in range(200)]
    rows += [(900, None, "big"), (901, "", "empty"), (7, rows[7][1], "big")]
    df, _ = documents(spark, rows)
    occ, w = mixing.plan_mix(df, max_repeats=2.0, block_tokens=100)
    weights = {r.source_key: r for r in w.collect()}
    assert sum(r.weight for r in weights.values()) == pytest.approx(1)
    rates = [r.rate for r in weights.values() if r.tokens]
    assert max(rates) / min(rates) == pytest.approx(2.0, rel=1e-6) and min(rates) == pytest.approx(1.0)
    got = occ.collect()
    times = defaultdict(int)
    for r in got:
        times[r.doc_id] += 1
    for i, _, s in rows:
        assert times[i] >= 1 and (times[i] <= 2 or i == 7)
    for s, r in weights.items():
        tokens = sum(g.n_tokens for g in got if (g.source or mixing.NO_SOURCE) == s)
        assert abs(tokens - r.target_tokens) <= 5 or not r.tokens
    for b in {g.block for g in got}:
        assert sorted(g.position for g in got if g.block == b) == list(range(sum(g.block == b for g in got)))
    kept = mixing.apply_mix(df, max_repeats=2.0)
    assert kept.columns == df.columns
    have = defaultdict(int)
    for r in kept.collect():
        have[r.doc_id] += 1
    assert have == times


def test_mixing_entropy_target_and_empty_table(spark):
    rows = [(i, "w " * 10, "a" if i < 90 else f"b{i % 4}") for i in range(120)]
    df, _ = documents(spark, rows)
    share = 0.9
    w = mixing.weights(mixing._lean(df, "doc_id", "source", "text"), share, 1e9).collect()
    h = -sum(r.weight * math.log(r.weight) for r in w)
    assert h == pytest.approx(share * math.log(len(w)), abs=1e-6)
    assert mixing.plan_mix(documents(spark, [])[0])[0].count() == 0
    assert mixing.apply_mix(documents(spark, [(1, None, None), (2, "", "x")])[0]).count() == 2


def test_mixing_keeps_columns_of_any_name(spark):
    rows = [(i, "a b", "x" if i % 3 else "y", i, 2 * i, 3 * i, 4 * i, f"r{i}", 5 * i) for i in range(30)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, _key long, _copies long, _until long, copy long, `row` string, full_epochs long")
    got = mixing.apply_mix(df)
    assert got.columns == df.columns and {tuple(r) for r in got.collect()} == set(rows)


def test_sources_without_tokens_are_dealt_over_blocks(spark):
    rows = [(i, "w " * 10, "a") for i in range(200)] + [(1000 + i, "", "b") for i in range(200)]
    occ, _ = mixing.plan_mix(documents(spark, rows)[0], block_tokens=100)
    got = occ.collect()
    assert len(got) >= 400 and len({r.block for r in got if r.source == "b"}) > 10


def test_exponent_equals_a_plain_bisection(spark):
    tokens = [5, 17, 100, 1000, 40000, 3]
    by = spark.createDataFrame([(t,) for t in tokens], "tokens long")
    p = np.array(tokens) / sum(tokens)

    def entropy(a):
        q = p**a / (p**a).sum()
        return -(q * np.log(q)).sum()

    for share, limit in ((0.8, 1e9), (1.0, 3.0), (0.5, 1.0), (0.0, 1e9)):
        lo, hi = 0.0, 1.0
        for _ in range(60):
            mid = (lo + hi) / 2
            lo, hi = (mid, hi) if entropy(mid) >= share * math.log(6) - 1e-12 else (lo, mid)
        least, most = 0.0, 1.0
        for _ in range(60):
            mid = (least + most) / 2
            r = p ** (mid - 1)
            least, most = (least, mid) if r.max() / r.min() <= limit else (mid, most)
        assert mixing.solve_exponent(by, float(sum(tokens)), share * math.log(6) - 1e-12, limit) == pytest.approx(max(lo, most if limit < 1e9 else 0.0), abs=1e-5)


# op2


def test_media_payloads_and_alignment(spark):
    df, rows = documents(spark)
    store = media.store_media(df.select(media.payload_of(F.col("text")).alias("payload")))
    feats = {r.payload_sha256: r for r in media.media_features(store).collect()}
    for _, t, _ in rows:
        raw = (t or "").encode()
        p = raw + b"\0" * (-len(raw) % 64 if raw else 64)
        r = feats[hashlib.sha256(p).hexdigest()]
        assert (r.digest, r.payload_bytes, r.tail_crc32) == (r.payload_sha256, len(p), zlib.crc32(p[-64:]))
        png = media.encode_png(p)
        assert media.decode_png(png) == p and hashlib.sha256(png).hexdigest() == r.media_sha256
    with pytest.raises(ValueError):
        media.decode_png(png[:40] + b"x" + png[41:])


def test_interleaved_items(spark):
    html = '<p>One &amp; two<figure><img src="sha256:aa" alt="alt"><figcaption>A  cap</figcaption></figure>three<script>x</script><img src="http://x/y.png">'
    rows = [(1, html), (2, None), (3, ""), (4, "<p>broken <b")]
    pages = spark.createDataFrame(rows, "page_id long, html string")
    got = {r.page_id: [(i.position, i.kind, i.text, i.digest, i.caption) for i in r["items"]] for r in media.interleave(pages).collect()}
    assert got[1] == [(0, "text", "One & two", None, None), (1, "media", None, "aa", "A cap"), (2, "text", "three", None, None), (3, "media", "http://x/y.png", None, None)]
    assert got[2] == got[3] == []
    bytes_of = spark.createDataFrame([("aa", 7)], "digest string, size int")
    flat = {(r.page_id, r.position): r["size"] for r in media.resolve(media.interleave(pages), bytes_of, ["page_id"]).collect()}
    assert flat[1, 1] == 7 and flat[1, 3] is None


@pytest.mark.parametrize(
    "html,want",
    [
        ('<img src="a"><img src="b" alt="own"><figcaption>stray</figcaption>', [("a", None), ("b", "own"), "stray"]),
        ('<img src="a"><figure><img src="b"><figure><img src="c"><figcaption>in</figcaption></figure><figcaption>out</figcaption></figure>', [("a", None), ("b", "out"), ("c", "in")]),
        ('<figure><figcaption>first<p>two</figcaption><img src="a"></figure><img src="b">', [("a", "firsttwo"), ("b", None)]),
        ('<template><img src="a">t</template><figure><img src="b"><figcaption>open', [("b", "open")]),
        ('</figure></figcaption>x<script><img src="a"></script>', ["x"]),
    ],
)
def test_captions_stay_with_their_figure(html, want):
    got = media.parse_items(html)
    assert [(i["text"] or i["digest"], i["caption"]) if i["kind"] == "media" else i["text"] for i in got] == want
    assert [i["position"] for i in got] == list(range(len(got)))


def test_payloads_are_resolved_by_digest(spark, monkeypatch):
    """Stored bytes come to their place in the page, also where one digest has most references."""
    from patchspace.llm import spread

    monkeypatch.setattr(spread, "HOT_ROWS", 4)
    texts = ["hot", *(f"t{i}" for i in range(6))]
    payloads = spark.createDataFrame([(t,) for t in texts], "text string").select(media.payload_of(F.col("text")).alias("payload"))
    store = media.store_media(payloads)
    digest = {t: hashlib.sha256(t.encode().ljust(64, b"\0")).hexdigest() for t in texts}
    use = lambda i: texts[0] if i % 3 else texts[1 + i % 6]
    pages = spark.createDataFrame([(i, f'<p>before {i}<img src="sha256:{digest[use(i)]}"><img src="sha256:00">') for i in range(40)], "page_id long, html string").repartition(3)
    got = media.resolve(media.interleave(pages), store, ["page_id"]).collect()
    assert len(got) == 120
    for r in got:
        if r.position == 1:
            assert media.decode_png(bytes(r.media)).rstrip(b"\0").decode() == use(r.page_id)
        else:
            assert r.media is None and (r.text == f"before {r.page_id}") == (r.position == 0)


def test_op2_features_equal_a_plain_computation(spark, tmp_path):
    df, rows = documents(spark)
    df.write.parquet(f"{tmp_path}/documents.parquet")
    got = media.op2(spark, str(tmp_path)).collect()
    assert len(got) == len(rows)
    texts = defaultdict(list)
    for i, t, _ in rows:
        texts[i].append((t or "").encode())
    for r in got:
        raw = next(x for x in texts[r.doc_id] if len(x) == r.n_bytes)
        p = raw + b"\0" * (-len(raw) % 64 if raw else 64)
        assert (r.payload_bytes, r.payload_sha256, r.caption) == (len(p), hashlib.sha256(p).hexdigest(), f"Text of document {'null' if r.doc_id is None else r.doc_id}")
        x = [list(p[k : k + 64]) for k in range(0, len(p), 64)]
        flat = [v for line in x for v in line]
        mean = sum(flat) / len(flat)
        std = math.sqrt(sum((v - mean) ** 2 for v in flat) / len(flat))
        parts = dict(f.split("=") for f in r.feature.split(";"))
        assert int(parts["h"]) == len(x) and abs(float(parts["mean"]) - mean) < 1e-4 and abs(float(parts["std"]) - std) < 1e-4


# op3


def test_warc_of_a_hot_payload(spark, monkeypatch):
    from patchspace.llm import spread

    monkeypatch.setattr(spread, "HOT_ROWS", 4)
    rows = [(i, f"u{i}", "h" * 200 if i % 2 else f"{i % 20} " * 100) for i in range(60)]
    got = {r.page_id: r.refers_to for r in warc.decide(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    first = {}
    for i, _, h in rows:
        first.setdefault(h, i)
    assert got == {i: None if first[h] == i else first[h] for i, _, h in rows}


def test_warc_round_trip(spark):
    long = "x" * 250 + "é"
    rows = [(9, "u9", long), (3, "u3", long), (4, None, "short"), (5, "u5", "short"), (6, "u6", None), (7, "u7", ""), (None, "un", long), (8, "u\r\n8", "y" * 3000)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3)
    folder = new_path(spark, "test-warc")
    manifest = warc.write_warc(warc.decide(pages), folder, chunk_bytes=100)
    got = defaultdict(list)
    for r in warc.read_warc(manifest, chunk_bytes=64).collect():
        got[r.page_id].append(r)
    for i, _, html in rows:
        raw = (html or "").encode()
        chunks = sorted(got[i], key=lambda r: r.chunk_no)
        assert {(c.declared_bytes, c.declared_digest) for c in chunks} == {(len(raw), hashlib.sha256(raw).hexdigest())}
        if i == 9:
            assert (chunks[0].record_type, chunks[0].refers_to) == ("revisit", 3)
        else:
            assert chunks[0].record_type == "response" and b"".join(c.data for c in chunks) == raw
            assert chunks[-1].sha256_so_far == hashlib.sha256(raw).hexdigest() and all(c.n_chunk <= 64 for c in chunks)
    path = manifest.first().path
    text = gzip.open(path.removeprefix("file:"), "rb").read()
    assert text.startswith(b"WARC/1.1\r\n")
    assert warc.read_warc(warc.write_warc(warc.decide(pages.limit(0)), new_path(spark, "test-warc"))).count() == 0


# op4


@pytest.mark.parametrize("scale", [1.0, 9.0])
def test_exact_top_k(spark, scale):
    rng = np.random.default_rng(2)
    vecs = [(i, (rng.normal(size=6) * scale).tolist()) for i in range(150)]
    vecs += [(200 + i, vecs[0][1]) for i in range(40)]  # ties
    bad = [(300, None), (301, [1.0, None]), (302, [float("nan")] * 6), (303, [float("inf")] * 6), (320, [0.5, 0.25])]
    df = spark.createDataFrame([(i, v, 1, 2) for i, v in vecs + bad], "vec_id long, embedding array<double>, block int, n int").repartition(3)
    got = annuli.top_k(df, F.col("vec_id") % 20 == 0, 20, n_pivots=4, block_rows=16).collect()
    ok = {i: np.pad(np.floor(64 * np.array(v)), (0, 6 - len(v))) for i, v in vecs + [bad[-1]]}
    for q in (i for i in ok if i % 20 == 0):
        want = sorted(((-int(ok[q] @ v), i) for i, v in ok.items() if i != q))[:20]
        have = sorted((r.rank, r.vec_id, r.score) for r in got if r.query_id == q)
        assert [(-s, i) for _, i, s in have] == want and [r for r, _, _ in have] == list(range(1, 21))
    assert annuli.top_k(df.limit(0), F.col("vec_id") % 20 == 0).count() == 0


def test_far_annuli_are_not_shuffled(spark):
    """Clusters far apart: a group of queries is paired with the blocks of its own cluster only."""
    rng = np.random.default_rng(3)
    centres = rng.normal(size=(6, 8)) * 40
    centres *= 100 / np.linalg.norm(centres, axis=1)[:, None]
    vecs = [(i, (centres[i % 6] + rng.normal(size=8) * 0.2).tolist()) for i in range(900)]
    df = spark.createDataFrame(vecs, "vec_id long, embedding array<double>").repartition(3)
    rows = annuli.integers(df)
    index, facts = annuli.build_index(rows, 5, F.col("vec_id") % 20 == 0, 24, 16, group_queries=4, group_rows=32)
    every = index.where("kind = 'query'").select("grp").distinct().count() * index.where("kind = 'block'").select("grp").distinct().count()
    assert annuli.pairs(index).count() < 0.6 * every
    got = annuli.search(index, facts, 5).collect()
    ok = {i: np.floor(64 * np.array(v)) for i, v in vecs}
    for q in range(0, 900, 20):
        want = sorted(((-int(ok[q] @ v), i) for i, v in ok.items() if i != q))[:5]
        assert [(-r.score, r.vec_id) for r in sorted((r for r in got if r.query_id == q), key=lambda r: r.rank)] == want


# op5


def page(i, body, nav="<nav><a>Menu</a></nav>", foot="<footer>&copy; all</footer>"):
    return (i, f"http://h.example/{i}", f"<html><head><title>T{i}</title><script>var a='</p>';</script></head><body>{nav}<div class='ad'>Buy</div>{body}{foot}</body></html>")


def test_main_text(spark):
    rows = [page(i, f"<article><h1>Head {i}</h1><p><b>A &amp; b{i}<br><p>x\n y&nbsp;z</p><div class='comments'>rude</div></article>") for i in range(6)]
    rows += [(20, None, None), (21, "http://h.example/21", ""), (22, "bad url", "plain <b>text</b> only"), page(23, "<article>" + "<p>long text</p>" * 3000 + "</article>"), (24, "u", "<article><p>open <"), rows[0]]
    df = spark.createDataFrame([(*r, 1, "x") for r in rows], "page_id long, url string, html string, n_pages int, host string").repartition(3)
    got = {r.page_id: r.text for r in template.main_text(df).collect()}
    for i in range(6):
        assert got[i] == f"Head {i}\nA & b{i}\nx y z"
    assert got[20] == got[21] == "" and got[22] == "plain text only" and got[23].count("\n") == 2999
    assert template.main_text(df).count() == len(rows) and template.main_text(df.limit(0)).count() == 0


def test_template_drops_fixed_wording_without_an_article(spark):
    rows = [(i, f"http://k.example/{i}", f"<body><div>Fixed slogan</div><div id='x'>Own words {i}</div><div>Always here</div><span>!</span></body>") for i in range(5)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    assert {r.text for r in template.main_text(df).collect()} == {f"Own words {i}" for i in range(5)}
    t = template.deduce(template.occurrences(template._pages(df, "page_id", "url", "html"))).collect()
    assert len(t) == 1 and '"<div.x"' in t[0].template


def given_style(i, rng):
    """A page of the given tables' shape, with a region that no list names, in and beside the article."""
    say = lambda n: " ".join(f"w{x}" for x in rng.integers(0, 500, n))
    nav = "".join(f"<li><a href='/{j}'>{say(1)}</a></li>" for j in range(5))
    return f"<!DOCTYPE html><html><head><title>T</title></head><body><nav><ul>{nav}</ul></nav><div class='teaser-x'>{say(4)}</div><div class='ad'>{say(3)}</div><article><h1>{say(4)}</h1><p><b>{say(30)}<br><p>{say(20)}</p><div class='k7'><p>Always the same words.</p></div><p>{say(9)}</p></article><footer>&copy; {say(3)}</footer></body></html>"


def test_the_template_decides_regions(spark):
    rng = np.random.default_rng(4)
    pages = [given_style(i, rng) for i in range(8)]
    # no article element: only the amount of text in the host's slots tells the story from the teasers
    plain = [p.replace("<article>", "<div class='s1'>").replace("</article>", "</div>") for p in pages]
    rows = [(i, f"http://a.example/{i}", p) for i, p in enumerate(pages)] + [(100 + i, f"http://b.example/{i}", p) for i, p in enumerate(plain)] + [(200, "http://c.example/1", pages[0]), (201, "http://c.example/2", plain[0])]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3)
    got = {r.page_id: r.text for r in template.main_text(df).collect()}
    off = {i: template.extract(h, template.Frame(None)) for i, _, h in rows}
    for i in range(8):
        assert "Always the same words." in off[i] and "Always the same words." not in got[i]
        assert got[i] == off[i].replace("Always the same words.\n", "")
        assert got[100 + i] == got[i] and off[100 + i] != got[i]
    assert got[200] == off[200] and got[201] == off[201]  # two pages are no template


def test_articles_that_repeat_are_no_template(spark):
    copies = [(i, "http://d.example/", "<html><body><nav>m</nav><article id='p7'><h1>Head</h1><p>same text</p></article></body></html>") for i in range(6)]
    shared = [(10 + i, "http://e.example/", f"<html><body><article><h1>H{i}</h1><p>shared passage</p><p>own {i}</p></article></body></html>") for i in range(6)]
    df = spark.createDataFrame(copies + shared, "page_id long, url string, html string")
    got = {r.page_id: r.text for r in template.main_text(df).collect()}
    assert got == {i: "Head\nsame text" for i in range(6)} | {10 + i: f"H{i}\nshared passage\nown {i}" for i in range(6)}


def test_classes_equal_those_of_whole_occurrence_vectors(spark):
    rng = np.random.default_rng(11)
    pages = [given_style(i, rng) + ("<p class='z'>tail</p><i></i><u></u>" if i % 3 else "") for i in range(12)]
    df = spark.createDataFrame([(i, "http://h.example/", p) for i, p in enumerate(pages)], "page_id long, url string, html string").repartition(4)
    vectors = defaultdict(lambda: [0] * len(pages))
    for i, p in enumerate(pages):
        for t in template.tokens(p):
            if t[0] == "tag":
                vectors[("</" if t[1] else "<") + t[3]][i] += 1
            elif t[1].split():
                vectors[template.text_key(" ".join(t[1].split()))][i] += 1
    classes = defaultdict(set)
    for token, v in vectors.items():
        if set(v) <= {0, 1} and sum(v) >= 6:
            classes[tuple(v)].add(token)
    want = {frozenset(c) for c in classes.values() if len(c) >= 3}
    found = json.loads(template.deduce(template.occurrences(template._pages(df, "page_id", "url", "html"))).first().template)
    assert {frozenset(c["tokens"]) for c in found["classes"]} <= want and len(want) == 2
    assert max(want, key=len) in {frozenset(c["tokens"]) for c in found["classes"]} and found["main"] == "<article"


@pytest.mark.parametrize(
    "body,want",
    [
        ("<p class='notice'>x</p><p>body</p>", "x\nbody"),
        ("<span hidden>x</span> <span>y</span><p hidden>z</p><p>body</p>", "y\nbody"),
        ("<p hidden>x<p>body<ul><li hidden>a<li>b</ul><div class='notice'><div>c</div></div>d", "body\nb\nd"),
        ("<span hidden>x<span>y</span>z</span>body", "body"),
        ("<div style='overflow:hidden'>a</div><div aria-hidden='false'>b</div><div data-title='The hidden valley' data-id='ad'>c</div>", "a\nb\nc"),
        ("<h2 id='search-algorithms'>a</h2><section id='social-history'>b</section><section id='related'>c</section><div class='ad'>d</div>", "a\nb"),
    ],
)
def test_text_beside_away_elements_stays(body, want):
    for tag in ("article", "main class='has-sidebar'", "article style='overflow:hidden'"):
        assert template.extract(f"<body><{tag}>{body}</{tag.split()[0]}></body>", template.Frame(None)) == want


def test_classes_nest():  # members: place, token, end, chars, fixed
    m = lambda place, token: (place, token, place, 1, False)
    out = template.nested([(4, [m(0.0, "<a"), m(5.0, "</a"), m(9.0, "<z")]), (3, [m(1.0, "<b"), m(2.0, "<c")]), (2, [m(4.0, "<d"), m(6.0, "<e")])])
    assert [c["tokens"] for c in out] == [["<a", "</a", "<z"], ["<b", "<c"]] and (out[1]["parent"], out[1]["slot"]) == (0, 1)


# op6


def test_quality_is_learnt_and_deterministic(spark):
    rng = np.random.default_rng(4)
    good, bad = [f"word{i}" for i in range(80)], [f"JUNK{i}!!" for i in range(80)]
    rows = [(i, " ".join(rng.choice(good if i % 2 else bad, 30)), "s") for i in range(400)]
    rows += [(1000, None, "s"), (1001, "", "s"), (None, "word1 word2", "s"), (1, rows[1][1], "s")]
    df, _ = documents(spark, rows)
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(400)] + [(None, 1, 0), (5000, 0, 0), (3, None, 0)], "doc_id long, quality int, toxic int")
    model = quality.fit(df, labels)
    got = df.select("doc_id", quality.scorer(model)(F.col("text")).alias("score")).collect()
    assert len(got) == len(rows) and all(0 <= r.score <= 1 for r in got)
    held = [r for r in got if r.doc_id is not None and r.doc_id < 400 and zlib.crc32(str(r.doc_id).encode()) % 5 == 0]
    assert sum((r.score >= 0.3) == (r.doc_id % 2 == 1) for r in held) / len(held) > 0.95
    again = quality.fit(df.repartition(2), labels)
    assert np.allclose(again.vectors, model.vectors) and again.temperature == model.temperature


def test_quality_without_labels(spark):
    df, rows = documents(spark)
    model = quality.fit(df, spark.createDataFrame([], "doc_id long, quality int"))
    assert {round(r.s, 9) for r in df.select(quality.scorer(model)(F.col("text")).alias("s")).collect()} == {0.5}
    empty, _ = documents(spark, [])
    assert empty.select(quality.scorer(quality.fit(empty, spark.createDataFrame([], "doc_id long, quality int")))(F.col("text"))).count() == 0


# op9


WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute_groups(rows, words, percent):
    sets = {}
    for i, t, _ in rows:
        w = WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (t or "")))
        sets[i] = frozenset(tuple(w[j : j + words]) for j in range(max(1, len(w) - words + 1))) if w else frozenset()
    up = {i: i for i in sets}

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for a in sets:
        for b in sets:
            if a is not None and b is not None and a < b and sets[a] and sets[b]:
                n = len(sets[a] & sets[b])
                if 100 * n >= percent * (len(sets[a]) + len(sets[b]) - n):
                    x, y = find(a), find(b)
                    up[max(x, y)] = min(x, y)
    return {i: (None if i is None else find(i), len(sets[i])) for i in sets}


@pytest.mark.parametrize("words,percent,leaf,group", [(3, 85, 2048, 8192), (5, 80, 8, 4)])
def test_near_duplicates(spark, words, percent, leaf, group):
    rng = np.random.default_rng(6)
    vocab = [f"V{i}" for i in range(500)]
    base = [list(rng.choice(vocab, 90)) for _ in range(12)]
    rows, n = [], 0
    for b in base:
        for edits in (0, 0, 1, 1, 2, 3, 6, 20):
            w = list(b)
            for at in rng.choice(90, edits, replace=False):
                w[at] = str(rng.choice(vocab))
            rows.append(((n * 37) % 1009, " ".join(w), "s"))
            n += 1
    rows += [(2000, "a b", "s"), (1999, "A  B\n", "s"), (2001, "a", "s"), (2002, "", "s"), (2003, None, "s"), (2004, " ", "s"), (None, rows[0][1], "s"), (2005, LONG, "s"), (2006, LONG + " tail", "s"), rows[3]]
    df, _ = documents(spark, rows)
    got = chosen_path.near_duplicates(df, words, percent, leaf_rows=leaf, group_rows=group).collect()
    want = brute_groups(rows, words, percent)
    assert len(got) == len(rows)
    for r in got:
        assert (r.component_id, r.n_shingles) == want[r.doc_id]
        assert r.kept == (r.doc_id is None or r.doc_id == r.component_id)


def hot_source(n=160, shared=84, own=16):
    """Texts of one source that share most words, in pairs that differ in some words."""
    rng = np.random.default_rng(9)
    common = [f"C{i}" for i in range(shared)]
    rows = []
    for i in range(0, n, 2):
        w = common + [f"P{i}x{j}" for j in range(own)]
        other = list(w)
        for at in rng.choice(shared, 2, replace=False):
            other[at] = f"Q{i}x{at}"
        rows += [(i, " ".join(w), "s"), (i + 1, " ".join(other), "s")]
    return rows


def linked(got):
    return {r.doc_id: r.component_id for r in got.collect()}


def test_near_duplicates_of_deep_nodes_reach_the_target_recall(spark):
    rows = hot_source()
    df, _ = documents(spark, rows)
    want = {i: c for i, (c, _) in brute_groups(rows, 3, 85).items()}
    assert len(set(want.values())) == 80
    assert linked(chosen_path.near_duplicates(df, 3, 85, trees=3, leaf_rows=4, recall=0.0)) != want
    assert linked(chosen_path.near_duplicates(df, 3, 85, trees=3, leaf_rows=4)) == want


def test_large_groups_are_confirmed_wholly(spark):
    rows = hot_source()
    df, _ = documents(spark, rows)
    want = {i: c for i, (c, _) in brute_groups(rows, 3, 85).items()}
    assert linked(chosen_path.near_duplicates(df, 3, 85, trees=2, leaf_rows=200, group_rows=8, recall=0.0)) == want


def test_shingles_of_many_rows_are_met_in_cells(spark, monkeypatch):
    monkeypatch.setattr(chosen_path, "CELL_ROWS", 3)
    rows = hot_source(60, 96, 4)
    df, _ = documents(spark, rows)
    each = df.select("doc_id", F.col("doc_id").alias("component")).where("doc_id IS NOT NULL")
    links = {(r.a, r.b) for r in chosen_path.exact_links(chosen_path.keyed_texts(df, "doc_id", "text", None), each, 1, 95).collect()}
    sets = {i: set(t.split()) for i, t, _ in rows}
    want = {(a, b) for a in sets for b in sets if b < a and 100 * len(sets[a] & sets[b]) >= 95 * len(sets[a] | sets[b])}
    assert want and links == want


def test_texts_that_share_an_identifier_are_told_apart(spark):
    a, b, c = (" ".join(f"{x}{i}" for i in range(40)) for x in "abc")
    rows = [(3, b, "s"), (5, a, "s"), (5, b, "s"), (7, a, "s"), (8, b, "s"), (9, c, "s"), (5, a, "s"), (11, c + " more", "s"), (2, c, "s"), (2, c + " tail", "s")]
    df, _ = documents(spark, rows)
    got = chosen_path.near_duplicates(df, 3, 85).join(df.select("doc_id", F.xxhash64("text").alias("text_key"), "text").distinct(), ["doc_id", "text_key"]).collect()
    assert len(got) == len(rows)
    component = {(r.doc_id, r.text): r.component_id for r in got}
    assert {k: component[k] for k in component if k[1] in (a, b)} == {(3, b): 3, (5, b): 3, (8, b): 3, (5, a): 5, (7, a): 5}
    assert {component[k] for k in component if k[1].startswith("c0")} == {2}
    assert {(r.doc_id, r.text) for r in got if r.first} - {(2, c), (2, c + " tail")} == {(3, b), (5, a)}
    assert sum(r.first and r.component_id == 2 for r in got) == 1


def test_near_duplicates_of_an_empty_table(spark):
    assert chosen_path.near_duplicates(documents(spark, [])[0]).count() == 0


def test_components(spark):
    from patchspace.llm.components import components

    edges = [(i, i + 1) for i in range(0, 40)] + [(100, 7), (200, 201), (201, 200), (5, 5)]
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(41)) and got[100] == 0 and got[201] == got[200] == 200


def test_components_of_hubs(spark, monkeypatch):
    from patchspace.llm import spread
    from patchspace.llm.components import components

    monkeypatch.setattr(spread, "HOT_ROWS", 5)
    monkeypatch.setattr(spread, "HOT_SHARE", 8)
    edges = [(1000, i) for i in range(1, 60)] + [(59, 2000), (2000, 2001), (3000, 3001)]
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 1 for i in [*range(1, 60), 1000, 2000, 2001]) and got[3000] == got[3001] == 3000
