"""Kernels, tokens, contamination, pages: against plain Python."""

from __future__ import annotations

import hashlib
import re
import zlib
from html import parser as html_parser

import numpy as np
import public_tokenizers as tokenizers_at
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from stratastore.llm import decontaminate, html, pieces, sharding, token_files
from stratastore.llm import textkernel as K
from stratastore.llm.queries import op2_sharding, op4_token_files, op10_html

WORDS = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
TEXTS = ["", None, "a", " ", "Hello  World", "x" * 400_000, "é ü\n\tß 漢字 ▁ 😀", "the the the", " lead and trail ", "A-b c_d 12"]


@settings(max_examples=80, deadline=None)
@given(st.lists(st.one_of(st.none(), st.text(max_size=60)), max_size=8))
def test_words_and_windows(texts):
    data, starts, ends, first, hashes = K.word_hashes(pa.array(texts, pa.string()), K.WORD)
    want = [WORDS.findall((t or "").translate(LOW)) for t in texts]
    assert [[bytes(data[a:b]).decode() for a, b in zip(starts[i:j], ends[i:j])] for i, j in zip(first[:-1], first[1:])] == want
    flat = [w for x in want for w in x]
    assert len(set(flat)) == len(set(hashes.tolist()))
    at, window = K.windows(hashes, first, 2)
    runs = [tuple(flat[p : p + 2]) for p in at]
    assert runs == [tuple(x[k : k + 2]) for x in want for k in range(len(x) - 1)] and len(set(runs)) == len(set(window.tolist()))


def test_long_words_and_index():
    long = "y" * 300_000
    _, _, _, _, h = K.word_hashes(pa.array([f"{long} {long}z {long}"]), K.WORD)
    assert h[0] == h[2] != h[1]
    keys = np.unique(np.random.default_rng(0).integers(0, 1 << 63, 5000, dtype=np.uint64))
    index = K.HashIndex(keys[:3000], bits=14)
    index.add(keys[3000:])
    assert (index.find(keys) == np.arange(len(keys))).all() and (index.find(keys + np.uint64(1))[~np.isin(keys + np.uint64(1), keys)] == -1).all()


# ---- pieces -------------------------------------------------------------------------------------

PIECES = tokenizers_at.path("piece_bpe_32k.model")


def best_sum(v: pieces.Vocabulary, text: str) -> float:
    best = [0.0] + [-np.inf] * len(text)
    for e in range(1, len(text) + 1):
        single = text[e - 1 : e] in v.plain
        for s in range(max(0, e - v.longest), e):
            if found := v.plain.get(text[s:e]):
                best[e] = max(best[e], best[s] + found[1])
        if not single:
            best[e] = max(best[e], best[e - 1] + v.unknown)
    return best[-1]


@pytest.mark.parametrize("text", ["the quick brown fox", "thtionable", "x" * 900, "äé漢😀 q", "a  b   c ", "abababab" * 150])
def test_viterbi_is_optimal_and_streams(text):
    v = pieces.Vocabulary.load(PIECES)
    escaped = pieces.MARK + text.replace(" ", pieces.MARK)
    search = pieces.StreamingViterbi(v)
    for c in escaped:
        search.push(c)
    ids = search.finish()
    assert ids == pieces.viterbi(v, escaped)
    byte = set(v.byte_ids)
    total, run = 0.0, []
    for i in ids:
        if i in byte:
            run.append(v.byte_ids.index(i))
        else:
            total += v.scores[i]
    total += len(bytes(run).decode()) * v.unknown
    assert abs(total - best_sum(v, escaped)) <= 1e-6 * abs(total)
    assert search.widest <= 4 * v.longest + 1


def test_window_stays_small_without_borders():
    v = pieces.Vocabulary.of({"a": (0, -1.0), "ab": (1, -1.5), "b": (2, -1.0), "ba": (3, -1.4), "aba": (4, -2.0)}, ["a", "ab", "b", "ba", "aba"], [-1, -1.5, -1, -1.4, -2], [0] * 256)
    search = pieces.StreamingViterbi(v)
    for _ in range(200):
        search.push("ab" * 500)
    ids = search.finish()
    assert "".join(v.pieces[i] for i in ids) == "ab" * 100_000 and search.widest <= 4 * v.longest + 1


def test_pieces_round_trip(spark):
    docs = spark.createDataFrame([(k, t, 1) for k, t in enumerate(TEXTS)], "doc_id long, text string, ids int")
    rows = pieces.decode(pieces.encode(docs, PIECES), PIECES, "_ids").collect()
    assert {r.doc_id: r.decoded for r in rows} == {k: (t or "").replace("▁", " ") for k, t in enumerate(TEXTS)}
    assert all(r.same for r in pieces.round_trip(docs, PIECES).collect())
    assert pieces.encode(docs.limit(0), PIECES).isEmpty()
    with pytest.raises(ValueError):
        pieces.PieceEncoder(pieces.Vocabulary.load(PIECES)).decode(np.array([99_999]), np.array([0, 1]))


# ---- token files --------------------------------------------------------------------------------


def test_token_files(spark):
    path = tokenizers_at.path("word_bpe_49k.json")
    library = token_files.WordTokenizer(path).library
    docs = spark.createDataFrame([*[(9 - k, t) for k, t in enumerate(TEXTS)], (None, "no id"), (3, "again")], "doc_id long, text string")
    out = token_files.write(docs, token_files.place(spark), path)
    rows = sorted(token_files.read(spark, out).collect(), key=lambda r: r.start)
    want = {(k, tuple([*library.encode(t or "", add_special_tokens=False).ids, 2])) for k, t in docs.collect()}
    assert {(r.doc_id, tuple(r.ids)) for r in rows} == want and [r.doc_id for r in rows][:2] == [None, 0]
    assert [r.start for r in rows] == np.concatenate(([0], np.cumsum([r.n_tokens for r in rows])[:-1])).tolist()
    crc = {r.start: r.ids_crc32 for r in token_files.crc_of_ids(token_files.read(spark, out)).collect()}
    assert crc == {r.start: zlib.crc32(np.array(r.ids, "<u4").tobytes()) for r in rows}
    plan = token_files.read(spark, out).where("doc_id = 5")._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(doc_id,5)" in plan
    empty = token_files.write(docs.limit(0), token_files.place(spark), path)
    assert token_files.read(spark, empty).isEmpty()


def test_tokenizers_that_join_over_white_space_get_whole_texts(tmp_path):
    from tokenizers import Tokenizer, models, pre_tokenizers

    library = Tokenizer(models.WordLevel({"a b": 0, "a": 1, "b": 2, "?": 3}, unk_token="?"))
    library.save(f"{tmp_path}/joins.json")
    joins = token_files.WordTokenizer(f"{tmp_path}/joins.json")
    library.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
    library.save(f"{tmp_path}/splits.json")
    splits = token_files.WordTokenizer(f"{tmp_path}/splits.json")
    texts = pa.array(["a b", None, "", "b", "a  b"])
    assert not joins.by_word and splits.by_word and token_files.WordTokenizer(tokenizers_at.path("word_bpe_49k.json")).by_word
    assert joins.encode(texts)[0].tolist() == [0, 2, 2, 2, 2, 2, 3, 2] and splits.encode(texts)[0].tolist() == [1, 2, 2, 2, 2, 2, 2, 1, 2, 2]


def test_token_files_have_row_indexes(spark, sf):
    from pyarrow import orc

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = token_files.write(docs, token_files.place(spark), tokenizers_at.path("word_bpe_49k.json"), n_parts=1)
    files = [orc.ORCFile(f) for f in spark.read.orc(f"{out}/data").inputFiles() for f in [f.removeprefix("file://")]]
    assert [(f.nrows, f.row_index_stride, f.compression, f.nstripes >= 1) for f in files] == [(200, token_files.ROW_INDEX_STRIDE, "ZSTD", True)]


def test_token_query(spark, sf):
    rows = op4_token_files(spark, sf).orderBy("doc_id").collect()
    assert len(rows) == 200 and all(a.start + a.n_tokens == b.start for a, b in zip(rows, rows[1:]))


# ---- shards -------------------------------------------------------------------------------------


def test_hypergeometric_law():
    import random
    from collections import Counter
    from math import comb

    rng, n = random.Random(1), 30_000
    seen = Counter(sharding.hypergeometric(rng, 6, 9, 7) for _ in range(n))
    assert all(abs(seen[k] / n - comb(6, k) * comb(9, 7 - k) / comb(15, 7)) < 0.012 for k in range(7))
    m = sharding.communication_matrix([5, 0, 900, 1], sharding.shard_sizes(906, 7), 3)
    assert [sum(r) for r in m] == [5, 0, 900, 1] and sorted(map(sum, zip(*m))) == [129] * 4 + [130] * 3


def test_shards_are_exact_and_native(spark, sf):
    out = op2_sharding(spark, sf)
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)
    rows = out.collect()
    by = {}
    for r in rows:
        by.setdefault(r.shard, []).append(r.slot)
    assert sorted(map(len, by.values())) == [12] * 8 + [13] * 8 and all(sorted(v) == list(range(len(v))) for v in by.values())
    text = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    assert all(r.text_crc32 == zlib.crc32(text[r.doc_id].encode()) and r["size"] == len(text[r.doc_id].encode()) + 1 for r in rows)


def test_shards_of_odd_rows(spark):
    odd = spark.createDataFrame([(None, None, 1)] * 40 + [(k, "t", 2) for k in range(3)], "doc_id long, text string, SHARD int")
    rows = sharding.shuffle_into_shards(odd, 4).collect()
    assert sorted(r._shard for r in rows).count(0) in (10, 11) and len({(r._shard, r.slot) for r in rows}) == 43
    assert sharding.shuffle_into_shards(odd.limit(0), 4).isEmpty()


def test_shards_keep_columns_of_any_name(spark):
    names = ("__part", "__r1", "__r2", "__place", "__block", "__cuts", "__start", "__n", "p", "c", "count", "slot")
    rows = spark.range(50).withColumns({c: F.lit(k) for k, c in enumerate(names)})
    out = sharding.shuffle_into_shards(rows, 4).collect()
    assert all(tuple(r[c] for c in names) == tuple(range(len(names))) for r in out) and len({r.id for r in out}) == 50
    assert sorted((r.shard, r._slot) for r in out) == [(s, k) for s, n in enumerate((13, 13, 12, 12)) for k in range(n)]


def test_shuffle_is_uniform(spark):
    rows = spark.range(4000).select(F.col("id").alias("doc_id"))
    where = {r.doc_id: (r.shard, r.slot) for r in sharding.shuffle_into_shards(rows, 8, seed=3).collect()}
    head = sum(where[k][0] < 4 for k in range(2000))
    assert 900 < head < 1100 and abs(np.corrcoef([where[k][1] for k in range(4000)], range(4000))[0, 1]) < 0.06


# ---- contamination ------------------------------------------------------------------------------


def brute(docs, items):
    toks = lambda t: WORDS.findall((t or "").translate(LOW))
    wins = {}
    for i, t in items:
        w = toks(t)
        width = min(13, len(w))
        for k in range(len(w) - width + 1) if width else ():
            wins.setdefault(width, {}).setdefault(tuple(w[k : k + width]), set()).add(str(i))
    out = []
    for d, t in docs:
        w, hit, who = toks(t), set(), set()
        for width, m in wins.items():
            for k in range(len(w) - width + 1):
                if x := m.get(tuple(w[k : k + width])):
                    hit |= set(range(k, k + width))
                    who |= x
        out.append((d, len(w), len(hit), len(who), hashlib.sha256(",".join(sorted(who)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    return sorted(out, key=repr)


@pytest.mark.parametrize("limit", [2_000_000, 60, 9])
def test_contamination(spark, monkeypatch, limit):
    monkeypatch.setattr(decontaminate, "MAX_WINDOWS", limit)
    long = " ".join(f"w{k}" for k in range(40))
    items = [(1, long), (2, "tiny one"), (3, None), (10, "..."), (4, "W0 w1, w2"), (5, long[:60])]
    docs = [(0, long), (1, "x " * 900 + long), (2, "A tiny; ONE here"), (3, None), (4, ""), (5, "w0 w1 w2 " * 3), (6, "tiny tiny one one"), (7, "y " * 10 + " ".join(f"w{k}" for k in range(5, 20))), (0, long)]
    found = decontaminate.find_contamination(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"))
    got = found.select("doc_id", "n_words", "n_hit", F.size("items"), F.sha2(F.array_join("items", ","), 256), "contaminated").collect()
    assert sorted(map(tuple, got), key=repr) == brute(docs, items)
    cut = {r.doc_id: r.text for r in decontaminate.remove_spans(found).collect()}
    assert cut[2] == "A  here" and cut[3] is None and cut[0] == ""
    assert {r.doc_id for r in decontaminate.remove_documents(found).collect()} == {3, 4} | {d for d, *_, c in brute(docs, items) if not c}


# ---- pages --------------------------------------------------------------------------------------


@pytest.mark.parametrize(("page", "want"), [
    (None, ""), ("", ""), ("<article>", ""), ("plain", "plain"),
    ("<body><nav>m</nav><header>h</header><article><h1>T &amp; U</h1><p>one<b>two</b> \n x&nbsp;y</p><div class='ad'>no</div></article><footer>f</footer>", "T & U onetwo x y"),
    ("<main><p>a<br>b<script>if(a<b)'<p>'</script></p><!-- <p>c</p> --><form>f</form><section id='comments'><article class='comment'>r</article></section><p title='>'>d</main>", "a b d"),
    ("<article>a<p>b<article>c</article>d</article>e", "a b c d"),
    ("<ARTICLE><P>&#233;&#x1F600;&lt;p&gt;</P><style>x</style><p hidden>n</p><aside>n</aside></ARTICLE>", "é😀<p>"),
    ("<div role=main><p>x</div><div>y</div>", "x"),
])
def test_main_text(page, want):
    assert html.main_text(page) == want


@pytest.mark.parametrize(("page", "want"), [
    ("<form id='aspnetForm'><article>text in a form<input name=x></article></form>", "text in a form"),
    ("<article><p class='notice'>a note<p>Real text <b>here</b></article>", "Real text here"),
    ("<article><section id='related-work'><h2>Related work</h2>Others did</section></article>", "Related work Others did"),
    ("<article><h2 id='search-results'>Search results</h2>x</article>", "Search results x"),
    ("<article class='comment-piece'>an opinion</article>", "an opinion"),
    ("<article>a<form>no</form><ul><li class=share>s<li>item</ul><div class='ad-slot'>n</div><div class='article-content'>c</div><p class='related-posts'>n</article>", "a item c"),
    ("<article><table><tr><td class=ad>z<td>k<tr><td>l</table><dl><dt>t<dd class='notice'>n<dd>d</dl></article>", "k l t d"),
    ("<form><p>a page that is one form<input></form>", "a page that is one form"),
])
def test_markup_as_it_is_found(page, want):
    assert html.main_text(page) == want


class Reader(html_parser.HTMLParser):
    """The same rules a second time: a parser of the standard library, on pages whose elements are all closed or void."""

    BREAKS = set("p h1 h2 h3 h4 br div section ul ol li article blockquote pre table tr td hr".split())

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.open, self.blocks, self.run = [], [], []

    def cut(self):
        if text := " ".join("".join(self.run).split()):
            self.blocks.append(text)
        self.run = []

    def handle_starttag(self, tag, attrs):
        if tag in self.BREAKS:
            self.cut()
        if tag in ("br", "hr", "img", "meta", "link", "input"):
            return
        named = " ".join(v or "" for k, v in attrs if k in ("class", "id")).split()
        self.open.append((tag, tag in ("nav", "aside", "footer", "form", "script", "style", "button") or any(x in ("ad", "comments", "cookie", "sidebar", "share") for x in named)))

    def handle_endtag(self, tag):
        if tag in self.BREAKS:
            self.cut()
        for k in range(len(self.open) - 1, -1, -1):
            if self.open[k][0] == tag:
                del self.open[k:]
                break

    def handle_data(self, data):
        if any(t == "article" for t, _ in self.open) and not any(out for _, out in self.open):
            self.run.append(data)


def test_pages_against_another_parser():
    for f in ("sf0.01", "sf0.1"):
        pages = pq.read_table(f"/root/testdata/{f}/pages.parquet", columns=["html"]).column(0).to_pylist()
        for page in pages:
            reader = Reader()
            reader.feed(page)
            reader.close()
            reader.cut()
            assert html.main_text(page) == " ".join(reader.blocks)


def test_clashing_names_of_pages(spark):
    rows = [(k, f"http://h/{k}", f"<p>one two three four five six seven</p><p>own{k}</p>") for k in range(4)]
    odd = spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({c: F.lit(c) for c in ("text", "host", "row", "body", "size", "starts", "r", "h", "i", "run")})
    for limit in (10**6, 3):
        got = {r.page_id: r._text for r in html.extract(odd, max_tokens=limit).collect()}
        assert got == {k: f"own{k}" for k in range(4)}


def test_hosts_lose_what_their_pages_share(spark):
    shared = "read more of our fine news every single day here"
    pages = [(k, f"http://a.org/{k}", f"<div>{shared}</div><p>page{k} " + " ".join(f"u{k}x{j}" for j in range(9)) + "</p>") for k in range(5)]
    pages += [(9, "http://b.org/", f"<p>{shared}</p>"), (10, None, None), (11, "http://a.org/m", f"<article>{shared}</article>")]
    df = spark.createDataFrame(pages, "page_id long, url string, html string")
    few = {r.page_id: r.text for r in html.extract(df).collect()}
    hot = {r.page_id: r.text for r in html.extract(df, max_tokens=10).collect()}
    assert few == hot and len(few) == 8
    assert "news" not in few[0] and few[0].startswith("page0 u0x0") and few[9] == few[11] == shared and few[10] == ""


def test_repeated_tokens_against_brute_force():
    rng = np.random.default_rng(2)
    for _ in range(30):
        sizes = rng.integers(0, 30, 6)
        first = np.concatenate(([0], np.cumsum(sizes)))
        tokens = rng.integers(0, 3, first[-1])
        want = np.zeros(len(tokens), bool)
        runs = {}
        for p in range(6):
            for k in range(first[p], first[p + 1] - 3):
                runs.setdefault(tuple(tokens[k : k + 4]), []).append((p, k))
        for spots in runs.values():
            if len({p for p, _ in spots}) >= 3:
                for _, k in spots:
                    want[k : k + 4] = True
        assert (html.repeated_tokens(tokens, first, 4, 3) == want).all()


def test_page_query(spark, sf):
    rows = op10_html(spark, sf).collect()
    raw = {r.page_id: r.html for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    import html as h

    for r in rows:
        inner = re.search(r"<article>(.*?)(</article>|$)", raw[r.page_id], re.S)[1]
        assert r.text == " ".join(h.unescape(re.sub(r"<[^>]*>", "", re.sub(r"</?(?:p|h1|br)>", "\n", inner))).split()) and r.n_chars == len(r.text)
