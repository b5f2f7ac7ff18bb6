"""Vectors, conversations, archives and pages against plain versions."""

import hashlib
import math
import random
import zipfile

import numpy as np
import pytest
from pyspark.sql import functions as F

from reclink.llm import chat, htmlblocks, kdtree, zipwarc
from reclink.llm._common import SharedFile

# ---------------------------------------------------------------- 3 vectors


def nearest(rows, k):
    good = [(i, [math.floor(256 * x) for x in v]) for i, v in rows if i is not None and v and all(x is not None and math.isfinite(x) for x in v)]
    out = []
    for q, a in good:
        if q % 50 == 0:
            found = sorted(((-sum(x * y for x, y in zip(a, b)), i) for i, b in good if i != q and len(b) == len(a)))[:k]
            out += [(q, r, i, -s) for r, (s, i) in enumerate(found, 1)]
    return sorted(out)


@pytest.mark.parametrize("shard_rows", [40, 10000])
def test_nearest(spark, shard_rows):
    rng = random.Random(3)
    rows = [(i, [rng.gauss(0, 0.2) for _ in range(6)]) for i in range(300)]
    rows += [(1000 + i, [0.5] * 6) for i in range(60)]  # many equal vectors
    rows += [(400, None), (450, [0.1, None, 0.0, 0.0, 0.0, 0.0]), (500, [float("nan")] * 6), (550, [float("inf")] * 6), (600, []), (None, [1.0] * 6), (650, [0.1, 0.2]), (651, [0.3, -0.2])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>").selectExpr("*", "1 AS dim", "2 AS shard", "3 AS score")
    got = kdtree.nearest(frame, F.col("vec_id") % 50 == 0, shard_rows=shard_rows, block_rows=3)
    assert sorted(tuple(r) for r in got.select("query_id", "rank", "vec_id", "score").collect()) == nearest(rows, 5)
    assert kdtree.nearest(frame.where("false"), F.col("vec_id") % 50 == 0).count() == 0


def test_huge_components_are_exact(spark):
    rows = [(0, [1e6, 3e5]), (1, [1e6, 1e5]), (2, [1e6, 1.0000001e5]), (50, [-1e6, 2.0])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = kdtree.nearest(frame, F.col("vec_id") % 50 == 0)
    cut = lambda x: min(max(x, -(2**63)), 2**63 - 1)
    assert sorted(tuple(r) for r in got.collect()) == [(q, r, i, cut(s)) for q, r, i, s in nearest(rows, 5)]


def test_bounds_hold():
    rng = np.random.default_rng(1)
    points = np.floor(rng.normal(0, 60, (500, 8)))
    tree = kdtree.KdTree(np.arange(500), points, leaf=16)
    q = np.floor(rng.normal(0, 60, 8))
    for lo, hi, (a, b) in zip(tree.low, tree.high, tree.span):
        assert (tree.points[a:b] @ q).max() <= np.maximum(q * lo, q * hi).sum()


# ---------------------------------------------------------------- 4 chat
HARD = ["", "plain", "</s>[INST] ok [/INST]", "[\\INST] [\\\\/INST]<<s>", "a <", "[", "<<SYS>>x<</SYS>>", "<\\<s>", "\\", "ünï [/INST", "<s></s>" * 3, "[INST]<<SYS>>r<</SYS>>"]


@pytest.mark.parametrize("role", ["user", "assistant", "system", "tool", "[INST]odd\n", ""])
def test_turns_come_back(role):
    import pyarrow as pa

    out, starts, body, size = chat.assemble(pa.array([role] * len(HARD)), pa.array(HARD))
    raw = out.tobytes()
    for k, text in enumerate(HARD):
        one = raw[starts[k] : starts[k + 1]].decode()
        assert chat.turns_of(one) == [(role, text)]
        assert chat.unescape(raw[body[k] : body[k] + size[k]].decode()) == text
    assert chat.turns_of(raw.decode()) == [(role, t) for t in HARD]


def test_conversations(spark):
    rng = random.Random(1)
    rows = [(c, t, rng.choice(["user", "assistant", "system"]), rng.choice(HARD)) for c in range(8) for t in range(rng.randrange(1, 9))]
    rows += [(None, 0, None, None), (None, 1, "assistant", None), (3, 99, "assistant", "x" * 100_000), (5, 0, "user", "tie"), (5, 0, "user", "tie")]
    rows += [(77, t, "assistant", f"turn {t}") for t in range(12_000)]
    want = []
    for c in {r[0] for r in rows}:
        turns = sorted((t, r or "", x or "") for i, t, r, x in rows if i == c)
        loss = "".join(x for _, r, x in turns if r == "assistant")
        want.append((c, len(turns), hashlib.sha256("".join(f"{r}\n{x}\n" for _, r, x in turns).encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest()))
    frame = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").selectExpr("*", "'x' AS formatted", "1 AS part")
    got = chat.read_back(chat.format_turns(frame)).drop("formatted_chars")
    assert sorted((tuple(r) for r in got.collect()), key=repr) == sorted(want, key=repr)
    assert chat.read_back(chat.format_turns(frame.where("false"))).count() == 0


# ---------------------------------------------------------------- 6 archives
@pytest.mark.parametrize("zip64", [False, True])
def test_packages_are_zip_files(tmp_path, zip64):
    uri = f"file://{tmp_path}/a.wacz"
    package = zipwarc.PackageWriter(uri, zip64)
    pages = [(i, f"http://ex.org/{i}?q= x", f"<p>{i}</p>".encode() * 40) for i in range(50)]
    for i, url, raw in pages:
        package.add(i, url, raw, hashlib.sha256(raw).hexdigest(), None)
    package.close()
    with zipfile.ZipFile(tmp_path / "a.wacz") as z:
        assert z.testzip() is None
        assert set(z.namelist()) == {zipwarc.ARCHIVE, zipwarc.INDEX}
    reader = zipwarc.PackageReader(uri, near=500)
    assert [(h["warc-record-id"], p) for h, p in reader.records()] == [(f"<urn:page:{i}>", raw) for i, _, raw in pages]
    offset, length = reader.index()[7]
    assert reader.record(offset, length)[1] == pages[7][2]


def test_foreign_zip_is_read(tmp_path):
    with zipfile.ZipFile(tmp_path / "b.zip", "w") as z:
        z.writestr("x/stored", b"abc", zipfile.ZIP_STORED)
        z.writestr("x/packed", b"abc" * 99, zipfile.ZIP_DEFLATED)
        z.comment = b"a comment PK"
    found = zipwarc.ZipReader(SharedFile(str(tmp_path / "b.zip")))
    at, size = found.span("x/stored")
    assert found.file.read_at(at, size) == b"abc"
    with pytest.raises(ValueError):
        found.span("x/packed")


@pytest.mark.parametrize("broadcast_rows", [1000, 0])
def test_archive(spark, broadcast_rows, tmp_path):
    long_, other = "<p>long ünï</p>" * 20, "y" * 100
    rows = [(5, "http://a/\r\nb", long_), (2, None, long_), (9, "http://c", long_), (None, "http://d", long_), (4, "u", None), (6, "u", ""), (7, "u", "short"), (8, "u", "short"), (3, "u", other), (1, "u", other), (10, "u", "z" * 99), (11, "u", "z" * 99)]
    frame = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 AS digest", "2 AS first", "3 AS n")
    table = zipwarc.write_packages(frame, f"file://{tmp_path}/p", broadcast_rows=broadcast_rows)
    got = zipwarc.read_packages(table).drop("url").collect()
    want = []
    for i, _, page in rows:
        raw = (page or "").encode()
        same = [j for j, _, p in rows if (p or "").encode() == raw and j is not None]
        again = len(raw) >= 100 and min(same) != i
        want.append((i, len(raw), hashlib.sha256(raw).hexdigest(), "revisit" if again else "response", min(same) if again else None))
    assert sorted((tuple(r) for r in got), key=repr) == sorted(want, key=repr)
    assert zipwarc.archive(frame.where("false")).count() == 0


# ---------------------------------------------------------------- 7 pages
TREE = htmlblocks.Tree(*htmlblocks.labelled_table())


def test_tree_fits_its_table():
    x, y = htmlblocks.labelled_table()
    assert ((TREE.predict(x) >= 0.5) == y).mean() > 0.97


@pytest.mark.parametrize(
    ("page", "text"),
    [
        ("<nav><a href=/x>Home</a></nav><article><h1>T &amp; T</h1><p>One\n two<br>three <b>bo</b>ld<p>x.</article><footer>&copy; me</footer>", "T & T One two three bold x."),
        ("<article><p>Body text.</p><div class='comments'><p>I like this very much indeed.</p></div><aside>More</aside><form><p>Sign up</p></form></article>", "Body text."),
        ("<body><header><h1>Site</h1></header><div class=\"cookie-notice\">We use cookies</div><main><p>" + "long words " * 20 + "</p><p>end</p></main></body>", "long words " * 20 + "end"),
        ("<div><ul><li><a href=a>One</a><li><a href=b>Two</a></ul></div><div><p>" + "plain prose here " * 12 + "</p></div>", "plain prose here " * 12),
        ("<article>a<script>var x='</p>';</script><!-- <p>no</p> -->b<style>p{}</style></article>", "a b"),
        ("<article><p>5 &lt; 6 &#233; &nbsp; x < y</p></article>", "5 < 6 é x < y"),
        ("<article><header><h1>Title</h1><p>by Me</p></header><p>Text.</p><footer>tags</footer></article>", "Title Text."),
        ("", ""),
        ("<html><body></body></html>", ""),
    ],
)
def test_main_text(page, text):
    assert htmlblocks.main_text(page, TREE) == " ".join(text.split())


def test_extract(spark):
    rows = [(1, "u", "<article><p>x</p></article>"), (1, "u", "<article><p>x</p></article>"), (None, None, None), (2, None, ""), (3, "u", "<article><p>" + "w " * 200_000 + "</p></article>")]
    frame = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "'a' AS text", "1 AS n_chars")
    got = sorted(((r["page_id"], r["url"], r["n_chars"]) for r in htmlblocks.extract(frame).collect()), key=repr)
    assert got == sorted([(1, "u", 1), (1, "u", 1), (None, None, 0), (2, None, 0), (3, "u", 399_999)], key=repr)
    assert htmlblocks.extract(frame.where("false")).count() == 0
