"""Operators on the given tables against separate means: another HTML parser, another record reader, other patterns, held-out labels."""

import io
import os
import re
import zlib
from html.parser import HTMLParser

import pytest

from elastipool.llm import htmltext, langid, pii, toxicity, warc

SF = "/root/testdata/sf0.01"
BLOCKS = {"p", "h1", "h2", "h3", "li", "ul", "ol", "div", "article", "body", "html", "nav", "footer", "header", "section", "aside", "form", "table", "tr", "td"}


@pytest.fixture(scope="module")
def given(spark):
    if not os.path.isdir(SF):
        pytest.skip("the given tables are not here")
    return lambda name: spark.read.parquet(f"{SF}/{name}.parquet")


class Lines(HTMLParser):
    """Lines of text of a page, or of its article alone."""

    def __init__(self, only_article):
        super().__init__(convert_charrefs=True)
        self.only, self.depth, self.skip, self.ad, self.lines, self.held = only_article, 0, 0, 0, [], []

    def end_line(self):
        text = " ".join("".join(self.held).split())
        self.lines += [text] if text else []
        self.held = []

    def handle_starttag(self, tag, attrs):
        if tag in BLOCKS:
            self.end_line()
        elif tag == "br":
            self.held.append(" ") if self.only else self.end_line()
        self.depth += tag == "article"
        self.skip += tag in ("script", "style", "head")
        self.ad += self.only and (self.ad > 0 and tag == "div" or dict(attrs).get("class") == "ad")

    def handle_endtag(self, tag):
        if tag in BLOCKS:
            self.end_line()
        self.depth -= tag == "article"
        self.skip -= tag in ("script", "style", "head")
        self.ad -= tag == "div" and self.ad > 0

    def handle_data(self, data):
        if not self.skip and not self.ad and (self.depth or not self.only):
            self.held.append(data)


def lines(html, only_article):
    p = Lines(only_article)
    p.feed(html)
    p.close()
    p.end_line()
    return "\n".join(p.lines)


def test_articles_by_another_parser(given):
    rows = given("pages").collect()
    got = {r.page_id: r.text for r in htmltext.extracted(given("pages")).collect()}
    assert all(got[r.page_id] == lines(r.html, True) for r in rows)


def read_one(data):
    """(headers, block) of one record, by lines."""
    f = io.BytesIO(data)
    assert f.readline().startswith(b"WARC/1.")
    head = {}
    while (line := f.readline().rstrip(b"\r\n")):
        k, v = line.split(b":", 1)
        head[k.decode().lower()] = v.strip().decode()
    block = f.read(int(head["content-length"]))
    assert f.read() == b"\r\n\r\n"
    return head, block


def test_derivatives_by_another_reader(given):
    pages = given("pages")
    source = {r.page_id: read_one(bytes(r.record)) for r in warc.captured(pages).collect()}
    html = {r.page_id: (r.url, r.html) for r in pages.collect()}
    seen = {}
    for r in warc.derived(warc.captured(pages), keep_bytes=True).collect():
        head, block = read_one(bytes(r.record))
        seen[r.page_id, head["warc-type"]] = head
        src, response = source[r.page_id]
        assert head["warc-refers-to"] == src["warc-record-id"] and head["warc-source-payload-digest"] == src["warc-payload-digest"] and head["warc-target-uri"] == html[r.page_id][0]
        assert response.split(b"\r\n\r\n", 1)[1].decode() == html[r.page_id][1]
        if head["warc-type"] == "conversion":
            assert block.decode() == lines(html[r.page_id][1], False)
        else:
            facts = dict(x.split(": ", 1) for x in block.decode().splitlines())
            assert facts["http-status-line"] == "HTTP/1.1 200 OK" and facts["payload-length"] == str(len(html[r.page_id][1].encode()))
    assert len(seen) == 2 * len(html) and all(seen[i, "metadata"]["warc-concurrent-to"] == seen[i, "conversion"]["warc-record-id"] for i in html)


MAIL = re.compile(r"[\w.+-]+@[\w-]+(?:\.[\w-]+)+")
ADDRESS = re.compile(r"(?<![\d.])(?:\d{1,3}\.){3}\d{1,3}(?![\d.])")


def test_surrogates_by_other_patterns(given):
    docs = given("documents").select("doc_id", "text")
    new = {r.doc_id: r.text for r in pii.redacted(docs).collect()}
    mails, ips, old_mails = {}, {}, set()
    for r in docs.collect():
        a, b = r.text or "", new[r.doc_id] or ""
        for kind, seen in ((MAIL, mails), (ADDRESS, ips)):
            x, y = kind.findall(a), kind.findall(b)
            assert len(x) == len(y), r.doc_id
            for p, q in zip(x, y):
                assert p != q and seen.setdefault(p.lower(), q.lower()) == q.lower()
        old_mails |= {m.lower() for m in MAIL.findall(a)}
        # what holds no entity stays as it is, byte by byte
        if not re.search(r"[@\d]|[Mm]r|[Mm]s|Herr|Frau|Se[nñ]or|Mme|Monsieur|Madame|Dr|(?i:secret|token|key|passw|pwd)", a):
            assert a == b
    assert mails and ips and len(set(mails.values())) == len(mails) and len(set(ips.values())) == len(ips) and not set(mails.values()) & old_mails


def test_toxicity_on_held_out_labels(given):
    docs, labels = given("documents"), given("labels").select("doc_id", "toxic")
    fold = lambda i: zlib.crc32(str(i).encode()) % 5
    lm, model = toxicity.models(docs, labels.where(langid.fold(labels["doc_id"], 5) != 0))
    got = {r.doc_id: r for r in toxicity.scored(docs, lm, model, langid.fold(docs["doc_id"], 5) == 0).collect()}
    held = [(got[r.doc_id].predicted, r.toxic) for r in labels.collect() if fold(r.doc_id) == 0]
    hit = sum(p and y for p, y in held)
    assert len(held) > 50 and hit >= 0.6 * sum(y for _, y in held) and hit >= 0.8 * max(1, sum(p for p, _ in held))


def test_languages_held_out(given):
    docs = given("documents").select("doc_id", "text", "lang")
    out = langid.fold(docs["doc_id"], 4) == 2
    got = {r.doc_id: r for r in langid.identified(docs, langid.fit(docs.where(~out)), out).collect()}
    held = [r for r in docs.collect() if zlib.crc32(str(r.doc_id).encode()) % 4 == 2]
    assert all(got[r.doc_id].held_out for r in held) and sum(got[r.doc_id].lang_pred == r.lang for r in held) >= 0.97 * len(held)
