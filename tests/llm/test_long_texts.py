"""Texts of megabytes: whole, in bounded pieces, by every operator that reads texts."""

import random
import zlib

import numpy as np
import pytest

from corpusdedup.llm import decontaminate, html_text, ngram_join, ngram_lm, packing, quality, token_files, warc


@pytest.fixture(scope="module")
def long_text():
    rng = random.Random(1)
    words = ["w%d" % rng.randrange(40_000) for _ in range(300_000)]
    words[299_000:299_000] = "a benchmark item near the very end of the long text".split()
    return " ".join(words)


def test_long_documents(spark, long_text):
    import public_tokenizers
    from tokenizers import Tokenizer

    assert len(long_text) > 1_500_000
    d = spark.createDataFrame([(1, long_text), (2, long_text.upper()), (3, "short")], "doc_id long, text string")
    n = len(long_text.split())
    join = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.similar_components(d).collect()}
    w = long_text.split()
    assert join[1] == join[2] == (len(set(zip(*(w[k:] for k in range(5)), strict=False))), 1) and join[3] == (1, 3)
    assert {r.doc_id: r.n_tokens for r in ngram_lm.fit_and_score(d)[0].collect()} == {1: n + 1, 2: n + 1, 3: 2}
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert {r.doc_id: r.n_words for r in quality.judge(d, quality.fit(d, none)).collect()} == {1: n, 2: n, 3: 1}
    assert sum(r.length for r in packing.pack(packing.word_lengths(d)).collect()) == 2 * (n + 1) + 2
    item = spark.createDataFrame([(7, "A benchmark item near the very end of the lang text")], "item_id long, text string")
    assert {r.doc_id: r.distance for r in decontaminate.find_matches(d, item).collect()} == {1: 1, 2: 1}
    path = public_tokenizers.path("word_bpe_49k.json")
    t = Tokenizer.from_file(path)
    want = zlib.crc32(np.array([*t.encode(long_text, add_special_tokens=False).ids, 2], "<u4").tobytes())
    got = {r.doc_id: r.ids_crc32 for r in token_files.read_ids(spark, *token_files.write_ids(d, path)).collect()}
    assert got[1] == got[2] == want


def test_long_pages(spark, long_text):
    html = f"<html><body><nav>Menu</nav><article><p>{long_text}</p></article></body></html>"
    pages = spark.createDataFrame([(1, "http://h/1", html), (2, "http://h/2", html)], "page_id long, url string, html string")
    assert [r.n_chars for r in html_text.extract(pages).collect()] == [len(long_text)] * 2
    got = {r.page_id: r for r in warc.read_archives(spark, *warc.write_archives(pages)).collect()}
    assert bytes(got[1].payload).decode() == html and got[2].refers_to == 1 and got[2].payload_bytes == len(html.encode())
