import datetime as dt
import gzip
import hashlib
import io
import struct
import zlib

import numpy as np
import pytest

from corrsentry.llm import media, revisit, urlrep


def test_urls_are_split_and_rules_chosen(spark):
    cases = {
        "http://A.Example.com/en/x?q#f": ("a.example.com", "/en/x", "example.com/en/", "block"),
        "https://www.example.com/en/": ("www.example.com", "/en/", "www.example.com/en/", "allow"),
        "https://m.www.example.com/en/1": ("m.www.example.com", "/en/1", "www.example.com/en/", "allow"),
        "https://badexample.com/en/": ("badexample.com", "/en/", "com/", "allow"),
        "http://x.net/es/": ("x.net", "/es/", "net/es/", "block"),
        "http://x.net/de/": ("x.net", "/de/", None, None),
        "http://x.com": ("x.com", "", None, None),
        "http://x.com?a/b": ("x.com", "", None, None),
        "ftp://u@H:8080/://y": ("u@h:8080", "/://y", None, None),
        "no scheme/en/": ("", "", None, None),
        "": ("", "", None, None),
        None: ("", "", None, None),
        "http://ÀB.com/\n/x": ("Àb.com", "/\n/x", "com/", "allow"),
    }
    pages = spark.createDataFrame([(i, u, "h") for i, u in enumerate(cases)], "page_id long, url string, host string")
    none = spark.createDataFrame([], "page_id long, good int")
    got = {r.page_id: r for r in urlrep.url_filter(pages, none).collect()}
    for i, (host, path, rule, verdict) in enumerate(cases.values()):
        assert (got[i].host, got[i].path, got[i].rule) == (host, path, rule)
        assert got[i].verdict == (verdict or got[i].verdict)
    assert urlrep.url_filter(pages.limit(0), none).count() == 0


def test_reputation_is_shrunk_by_level(spark):
    rows, y = [], []
    for h, n, rate in [("a.bad.org", 40, 0.1), ("b.bad.org", 40, 0.2), ("c.bad.org", 1, 1.0), ("a.good.org", 40, 1.0), ("b.good.org", 40, 0.9), ("c.good.org", 1, 0.0), ("new.bad.org", 0, 0), ("new.good.org", 0, 0)]:
        for i in range(max(n, 1)):
            rows.append((len(rows), f"http://{h}/{i}"))
            if n:
                y.append((len(rows) - 1, int(i < n * rate)))
    pages, y = spark.createDataFrame(rows, "page_id long, url string"), spark.createDataFrame([*y, (10**6, 1), (None, 1), (0, None)], "page_id long, good int")
    got = {r.host: r for r in urlrep.url_filter(pages, y, rules=[]).dropDuplicates(["host"]).collect()}
    assert got["a.bad.org"].good_rate < got["new.bad.org"].good_rate < got["c.bad.org"].good_rate < 0.9
    assert got["c.good.org"].good_rate > got["new.bad.org"].good_rate
    assert got["a.bad.org"].verdict == "block" and got["a.good.org"].verdict == "allow" and got["new.bad.org"].verdict == "block"
    assert all(r.bound < r.good_rate for r in got.values())


def test_plan_has_no_python(spark, capsys):
    pages, y = spark.createDataFrame([(1, "http://a.b/c")], "page_id long, url string"), spark.createDataFrame([(1, 1)], "page_id long, good int")
    urlrep.url_filter(pages, y).explain()
    assert not any(x in capsys.readouterr().out for x in ("Python", "Pandas", "Arrow", "NestedLoop", "Cartesian"))


def test_canonical_urls(spark):
    cases = {"HTTP://www.A.com:80/x/?utm_source=f&q=1#t": "a.com/x?q=1", "https://a.com/x?q=1&ref=y": "a.com/x?q=1", "a.com/x?q=1": "a.com/x?q=1", "https://user@b.org": "b.org", "https://b.org/?ref=1": "b.org", None: None}
    df = spark.createDataFrame([(i, u) for i, u in enumerate(cases)], "i int, url string")
    got = {r.i: r.c for r in df.select("i", revisit.canonical_url(df["url"]).alias("c")).collect()}
    assert [got[i] for i in range(len(cases))] == list(cases.values())


def test_revisits_against_a_scan_of_all_responses(spark):
    rng = np.random.default_rng(5)
    rows = []
    for i in range(600):
        url = ["http://a.com/1", "https://www.a.com/1/", "http://a.com/2", f"http://b.org/{i % 9}", None][int(rng.choice(5, p=[0.3, 0.2, 0.2, 0.28, 0.02]))]
        ts = None if i % 97 == 0 else dt.datetime(2024, 1, 1, tzinfo=dt.timezone.utc) + dt.timedelta(seconds=int(rng.integers(0, 300)))
        h = {"etag": ["W/\"a\"", "\"a\"", "\"b\""][i % 3], "content-type": "x", "n": str(i)} if i % 4 else {"last-modified": str(i % 2)} if i % 8 else None
        rows.append((i, url, ts, bool(i % 2), h, "d" if i % 5 else None, 0))
    df = spark.createDataFrame(rows, "id long, url string, ts timestamp, is_revisit boolean, headers map<string,string>, digest string, full int")
    canon = {r.id: r.c for r in df.select("id", revisit.canonical_url(df["url"]).alias("c")).collect()}
    want = {}
    for i, u, ts, again, h, d, _ in rows:
        if not again:
            continue
        old = [r for r in rows if not r[3] and u and ts and r[2] and canon[r[0]] == canon[i] and r[2] < ts]
        o = max(old, key=lambda r: (r[2], r[0]), default=None)
        own, was = h or {}, (o[4] or {}) if o else {}
        pair = lambda k: (own.get(k), was.get(k))  # noqa: B023, E731
        if o is None:
            v = "missing"
        elif all(pair("etag")):
            v = "etag" if pair("etag")[0].replace("W/", "") == pair("etag")[1].replace("W/", "") else "mismatch"
        elif all(pair("last-modified")):
            v = "last-modified" if len(set(pair("last-modified"))) == 1 else "mismatch"
        elif d and o[5]:
            v = "digest"
        else:
            v = "unverified"
        merged = was | {k: x for k, x in own.items() if k != "content-type"} if v in ("etag", "last-modified", "digest") else None
        want[i] = (o[0] if o else None, v, merged)
    for buckets in (1, 7, 64):
        got = {r.id: (r.response_id, r.verdict, r.headers) for r in revisit.resolve_revisits(df, buckets).collect()}
        assert got == want
    assert revisit.resolve_revisits(df.limit(0)).count() == 0


def test_warc_files_are_read_back(spark, tmp_path):
    a = revisit.write_warc("<urn:1>", "response", "http://a.com/", "2024-01-01T00:00:00Z", "200 OK", {"ETag": '"x"', "Content-Type": "text/html"}, b"body \r\n\r\n\xff")
    b = revisit.write_warc("<urn:2>", "revisit", "http://a.com/#f", "2024-01-02T00:00:00Z", "304 Not Modified", {"ETag": 'W/"x"', "Date": "now"})
    c = revisit.write_warc("<urn:3>", "metadata", "http://a.com/", "2024-01-02T00:00:00Z", "200 OK", {})
    (tmp_path / "plain.warc").write_bytes(a + c + b)
    (tmp_path / "packed.warc.gz").write_bytes(gzip.compress(a) + gzip.compress(b) + gzip.compress(a)[:20])
    (tmp_path / "cut.warc").write_bytes(a[:-30])
    (tmp_path / "empty.warc").write_bytes(b"")
    found = revisit.read_warc(spark, str(tmp_path))
    rows = sorted(found.collect(), key=lambda r: r.record_id)
    assert [r.record_id for r in rows] == ["<urn:1>"] * 2 + ["<urn:2>"] * 2
    assert rows[0].body == b"body \r\n\r\n\xff" and rows[0].status == 200 and rows[3].body is None
    caps = found.selectExpr("record_id id", "url", "ts", "kind = 'revisit' is_revisit", "headers", "digest").dropDuplicates(["id"])
    got = revisit.resolve_revisits(caps).collect()
    assert [(r.id, r.response_id, r.verdict) for r in got] == [("<urn:2>", "<urn:1>", "etag")]
    assert got[0].headers == {"etag": 'W/"x"', "content-type": "text/html", "date": "now"}


def bmp(a, bits):
    h, w = a.shape[:2]
    stride = (w * bits + 31) // 32 * 4
    rows = b"".join(bytes(r[:, 2::-1].tobytes() if bits == 24 else np.dstack([r[None, :, 2::-1], np.zeros((1, w, 1), np.uint8)]).tobytes()).ljust(stride, b"\0") for r in a[::-1])
    return b"BM" + struct.pack("<IIIIiiHHIIiiII", 54 + len(rows), 0, 54, 40, w, h, 1, bits, 0, len(rows), 0, 0, 0, 0) + rows


def test_formats_decode_to_the_same_samples():
    rng = np.random.default_rng(2)
    g, c, m = rng.integers(0, 256, (5, 11), np.uint8), rng.integers(0, 256, (5, 11, 3), np.uint8), rng.integers(0, 2, (5, 11), np.uint8)
    text = lambda a: " ".join(map(str, a.ravel())).encode()
    assert (media.decode(b"P5\n# note\n11 5\n255\n" + g.tobytes()) == g).all()
    assert (media.decode(b"P2 11 5 255\n" + text(g)) == g).all()
    assert (media.decode(b"P6 11 5 255\n" + c.tobytes()) == c).all()
    assert (media.decode(b"P3 11 5 255\n" + text(c)) == c).all()
    assert (media.decode(b"P5 11 5 1000\n" + (g.astype(np.uint16) * 3).astype(">u2").tobytes()) == g.astype(np.uint16) * 3).all()
    assert (media.decode(b"P4 11 5\n" + np.packbits(m, axis=1).tobytes()) == (1 - m) * 255).all()
    assert (media.decode(b"P1 11 5\n" + text(m).replace(b" ", b"")) == (1 - m) * 255).all()
    for bits in (24, 32):
        assert (media.decode(bmp(c, bits)) == c).all()
    for broken in (b"", b"P5", b"P5 3 3 255\n12", b"P9 1 1 255\n1", b"BM12", bmp(c, 24)[:70]):
        with pytest.raises((ValueError, struct.error)):
            media.decode(broken)


def test_area_resize_is_the_mean_of_the_source_area():
    rng = np.random.default_rng(7)
    a = rng.integers(0, 256, (7, 10)).astype(float)
    fine = np.kron(a, np.ones((6, 9)))  # 42 x 90: divides by 6 x 9 cells of any of the sizes below
    for h, w in ((7, 10), (1, 1), (6, 9), (3, 5), (14, 30)):
        want = fine.reshape(h, 42 // h, w, 90 // w).mean((1, 3))
        assert np.allclose(media.area_resize(a, h, w), want)
    assert media.area_resize(np.zeros((4, 4, 3)), 2, 2).shape == (2, 2, 3)


def test_tiles_and_hashes(spark):
    a = np.arange(40 * 50, dtype=np.uint8).reshape(40, 50)
    tiles = {(y, x): np.load(io.BytesIO(t)) for y, x, t in media.npy_tiles(a, 32)}
    assert (np.block([[tiles[0, 0], tiles[0, 1]], [tiles[1, 0], tiles[1, 1]]]) == a).all()
    ramp = np.tile(np.arange(90, dtype=np.uint8), (40, 1))
    assert media.difference_hash(ramp) == 2**64 - 1 and media.difference_hash(ramp[:, ::-1]) == 0
    df = spark.createDataFrame([(1, b"P5 90 40 255\n" + ramp.tobytes(), 5), (2, b"junk", 5), (3, None, 5)], "id long, data binary, npy int")
    got = media.media_tiles(df).collect()
    assert [(r.id, r.ok, r.dhash) for r in got if not r.ok] == [(2, False, None), (3, False, None)]
    assert sorted((r.tile_row, r.tile_col) for r in got if r.ok) == [(0, 0), (0, 1), (1, 0), (1, 1)]


def test_texts_come_back_from_their_stored_form(spark, docs, none):
    got = media.text_media(docs).collect()
    texts = {r.doc_id: (r.text or "").encode() for r in docs.collect()}
    assert sorted(r.doc_id for r in got) == sorted(r.doc_id for r in docs.collect())
    for r in got:
        raw = texts[r.doc_id]
        payload = raw + bytes((-len(raw)) % 64 or (0 if raw else 64))
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
        assert r.media_bytes > r.payload_bytes
    assert media.text_media(none).count() == 0


def test_long_images_are_summed_in_stripes_as_at_once():
    rng = np.random.default_rng(7)
    a = rng.integers(0, 256, (10_007, 64), dtype=np.uint8)
    assert np.allclose(media._stripe_sums(a, 9, 1000), media._stripe_sums(a, 9, 1 << 20), rtol=0, atol=1e-6)
    assert media._stripe_sums(a, 10_007).tolist() == a.astype(float).tolist()


def test_gzip_members_are_read_one_after_the_other():
    import gzip

    plain = [bytes([i]) * (i * 5000) for i in range(1, 30)]
    raw = b"".join(gzip.compress(p) for p in plain)
    assert list(revisit._members(raw)) == plain and list(revisit._members(raw + b"junk")) == plain
    assert list(revisit._members(raw + b"\x1f\x8b\x08damaged"))[:29] == plain
