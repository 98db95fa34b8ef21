"""Media, archives and pages: exact round trips, planted formats, differencing."""

import base64
import gzip
import hashlib
import io
import os
import random
import struct
import zipfile
import zlib

import pytest

from hyperpattern.llm import html_text, media, warc


def png():
    chunk = lambda k, d: struct.pack(">I", len(d)) + k + d + struct.pack(">I", zlib.crc32(k + d))
    return b"\x89PNG\r\n\x1a\n" + chunk(b"IHDR", struct.pack(">IIBBBBB", 1, 1, 8, 0, 0, 0, 0)) + chunk(b"IDAT", zlib.compress(b"\0\0")) + chunk(b"IEND", b"")


def zipped():
    out = io.BytesIO()
    with zipfile.ZipFile(out, "w") as z:
        z.writestr("a", "hello")
    return out.getvalue()


GIF = b"GIF89a" + struct.pack("<HHBBB", 1, 1, 0x80, 0, 0) + b"\0\0\0\xff\xff\xff\x2c" + struct.pack("<HHHHB", 0, 0, 1, 1, 0) + b"\x02\x02\x4c\x01\x00\x3b"
JPEG = b"\xff\xd8\xff\xe0\x00\x04ab\xff\xda\x00\x02xy\xff\x00z\xff\xd9"
BMP = b"BM" + struct.pack("<IIIIII", 30, 0, 26, 12, 1, 1) + b"abcd"
PDF = b"%PDF-1.4\nstuff\nstartxref\n0\n%%EOF"
KINDS = {"image/png": png(), "application/zip": zipped(), "image/gif": GIF, "image/jpeg": JPEG, "image/bmp": BMP, "application/gzip": gzip.compress(b"x" * 999), "audio/wav": media.to_wav(b"s" * 192), "application/pdf": PDF}


@pytest.mark.parametrize("kind", KINDS)
def test_formats(kind):
    b = KINDS[kind]
    assert media.sniff(b)[0] == (kind, 0, len(b))
    assert (kind, 5, len(b)) in media.sniff(b"12345" + b + b"tail")
    assert all(k != kind or at for k, at, _ in media.sniff(b[:-3]))


def test_sniffing_column(spark):
    rows = [(1, "image/png", bytearray(GIF), "x"), (2, "text/plain", bytearray(b"hi" + png()), "x"), (3, None, None, "x"), (4, "image/gif", bytearray(b"GIF89a junk"), "x"), (5, "image/gif", bytearray(), "x")]
    df = spark.createDataFrame(rows, "id long, declared string, bytes binary, carved string")
    got = {r["id"]: r for r in media.sniff_media(df, "bytes", "declared").collect()}
    assert got[1]["media_type"] == "image/gif" and got[1]["type_corrected"] and got[1]["media_length"] == len(GIF)
    assert got[2]["media_type"] == "text/plain" and bytes(got[2]["carved"][0]["bytes"]) == png()
    assert got[3]["media_type"] == got[4]["media_type"] == got[5]["media_type"] == "application/octet-stream"
    assert media.sniff_media(df.limit(0), "bytes").count() == 0


def test_texts_as_media(spark):
    texts = ["hello", "", None, "é" * 100, "x" * 192, "hello", "y" * 500_000]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r for r in media.read_media(media.store_texts(docs)).collect()}
    for i, t in enumerate(texts):
        raw = (t or "").encode()
        payload = raw + b" " * (-len(raw) % 192 if raw else 192)
        r = got[i]
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]))
        m = media.to_wav(payload)
        assert (r["media_bytes"], r["media_sha256"]) == (len(m), hashlib.sha256(m).hexdigest()) and r["feature"].startswith("audio/wav;")
    assert got[0]["feature"] == got[5]["feature"]


def test_chunked_framing():
    for n in (0, 1, 8192, 8193, 50_000):
        assert warc.unchunked(warc.chunked(b"z" * n)) == b"z" * n
    with pytest.raises(ValueError):
        warc.unchunked(warc.chunked(b"z" * 100)[:-20])
    with pytest.raises(ValueError):
        warc.unchunked(b"5;x=1\r\nabc")


def test_archives(spark):
    rows = [(1, "u", "x" * 100_000, 1), (5, "u", "é" * 50_000, 1), (2, "u", None, 1), (3, "v", "", 1), (9, None, "x" * 100_000, 1), (7, "a\r\nb", "q", 1), (7, "a\r\nb", "q", 1)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, digest long")
    got = {r["page_id"]: r for r in warc.round_trip(pages, 1000).collect()}
    first = {}
    for i, _, h, _ in sorted(rows):
        first.setdefault(h or "", i)
    assert len(got) == 6 and warc.round_trip(pages, 1000).count() == 7
    for i, _, h, _ in rows:
        b = (h or "").encode()
        want = (len(b), base64.b32encode(hashlib.sha1(b).digest()).decode(), "response" if first[h or ""] == i else "revisit", None if first[h or ""] == i else first[h or ""])
        assert tuple(got[i][c] for c in ("payload_bytes", "payload_digest", "record_type", "refers_to")) == want
    assert warc.round_trip(pages.limit(0)).count() == 0


def test_archives_with_repeated_and_null_ids(spark):
    big, other = "x" * 50_000, "é" * 40_000
    rows = [(1, big), (1, big), (2, big), (None, big), (None, other), (None, other), (4, "a" * 70_000), (4, "b" * 70_000), (4, None), (5, "")]
    pages = spark.createDataFrame([(i, "u", h) for i, h in rows], "page_id long, url string, html string")
    digest = lambda h: base64.b32encode(hashlib.sha1((h or "").encode()).digest()).decode()
    want = [(1, big, "response", None), (1, big, "response", None), (2, big, "revisit", 1), (None, big, "revisit", 1), (None, other, "response", None), (None, other, "response", None), (4, "a" * 70_000, "response", None), (4, "b" * 70_000, "response", None), (4, None, "response", None), (5, "", "revisit", 4)]
    key = lambda r: tuple(map(str, r))
    got = [tuple(r[c] for c in ("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")) for r in warc.round_trip(pages).collect()]
    assert sorted(got, key=key) == sorted([(i, len((h or "").encode()), digest(h), kind, to) for i, h, kind, to in want], key=key)


def test_a_missing_segment_is_told(spark):
    pages = spark.createDataFrame([(1, "u", "x" * 5000)], "page_id long, url string, html string").selectExpr("*", "cast(null as long) origin", "false repeated")
    records = warc.read_archives(warc.write_archives(pages, 1000))
    assert warc.reassembled(records).first()["complete"]
    assert not warc.reassembled(records.where("segment <> 3")).first()["complete"]


PAGE = "<html><head><title>t</title></head><body><nav>menu</nav><div class='ad'>buy</div>%s<footer>f</footer></body></html>"


@pytest.mark.parametrize(
    "html, want",
    [
        (PAGE % "<article><h1>T&amp;T</h1><p>a\n <b>b</b><br>c<p>d</article>", "T&T\n\na b c\n\nd"),
        (PAGE % "<main><section><p>one</p><aside>no</aside><p>two</p></section><div id=comments><p>c</p></div></main>", "one\n\ntwo"),
        ("<nav>never closed<article><p>x</p></article>", "x"),
        ("<article><script>var t='</p>'</script><p>k<!-- c -->l</p><form><p>no</p></form>a < b</article>", "kl\n\na < b"),
        ("<article><p hidden>no</p><p>yes &lt;tag&gt; &#233;</p></article>", "yes <tag> é"),
        ("", ""),
        (None, ""),
        ("<p>", ""),
    ],
)
def test_structure(html, want):
    assert html_text.main_text(html or "", None) == want


def test_differencing(spark):
    body = "<html><body><div><p>Site name</p></div><div><p>Story %d here</p><p>More of %d</p></div><p>Imprint</p></body></html>"
    rows = [(i, f"http://h.x/a/{i}", body % (i, i), "z") for i in range(6)] + [(10, "http://other/", body % (77, 77), "z"), (11, "http://h.x/a/3", body % (3, 3), "z"), (12, None, None, "z")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, text string")
    got = {r["page_id"]: r["text"] for r in html_text.extract(pages).collect()}
    for i in (*range(6), 11):
        k = 3 if i == 11 else i
        assert got[i] == f"Story {k} here\n\nMore of {k}"
    assert got[10] == "Site name\n\nStory 77 here\n\nMore of 77\n\nImprint" and got[12] == ""
    assert html_text.extract(pages.limit(0)).count() == 0


def test_differencing_passes_copies_over(spark):
    page = "<html><body><p>Site</p><div><p>%s</p></div><p>Imprint</p></body></html>"
    rows = [(i, "http://h/a/1", page % "one") for i in range(3)] + [(7, "http://h/a/2", page % "two"), (8, "http://h/b", page % "<article>Site</article>"), (9, "http://h/a/1", None), (None, "http://h/a/1", page % "one")]
    got = {(r["page_id"], r["text"]): r for r in html_text.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert set(got) == {(0, "one"), (1, "one"), (2, "one"), (7, "two"), (8, "Site"), (9, ""), (None, "one")}
    assert got[0, "one"]["n_shared"] == got[7, "two"]["n_deleted"] == 2 and got[8, "Site"]["n_deleted"] == 0


def test_differencing_against_a_plain_version(spark):
    r = random.Random(4)
    word = lambda: "".join(r.choice("abcd") for _ in range(3))
    rows = []
    for i in range(60):
        body = "".join(f"<p>{r.choice(['top', 'more', word(), word()])}</p>" for _ in range(r.randint(0, 8)))
        rows.append((i, f"http://h{r.randint(0, 2)}/{r.choice('ab')}/{r.randint(0, 30):02}", f"<body><nav>menu</nav><p>top</p>{body}<p>end</p></body>"))
    got = {x["page_id"]: x["text"] for x in html_text.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    hosts = {}
    for i, url, html in rows:
        host, path = html_text.place(url)
        found = [t for t, _ in html_text.blocks(html)]
        same = hosts.setdefault(host, {})
        same[tuple(found)] = min(same.get(tuple(found), path), path)
    for i, url, html in rows:
        host, _ = html_text.place(url)
        found = tuple(t for t, _ in html_text.blocks(html))
        path = hosts[host][found]
        alike = lambda p: len(os.path.commonprefix([p, path]))  # noqa: E731, B023
        others = [(alike(p), x) for x, p in hosts[host].items() if x != found]
        if not others:
            continue
        most = max(n for n, _ in others)
        wants = set()
        for n, other in others:  # any of the nearest will do
            if n == most:
                table = [[0] * (len(other) + 1) for _ in range(len(found) + 1)]
                for x in range(len(found)):
                    for y in range(len(other)):
                        table[x + 1][y + 1] = table[x][y] + 1 if found[x] == other[y] else max(table[x][y + 1], table[x + 1][y])
                wants.add(table[-1][-1])
        left = len(got[i].split("\n\n")) if got[i] else 0
        assert len(found) - 1 - left in {n - 1 for n in wants}, i  # the menu is out by its zone, and shared by all


def test_common_subsequence():
    assert html_text.common_subsequence([1, 2, 3, 2, 5], [2, 3, 9, 2]) == [1, 2, 3]
    assert html_text.common_subsequence([], [1]) == []
