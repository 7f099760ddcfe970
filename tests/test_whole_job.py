"""Queries must do the whole job: every document, every symbol, every value."""

from ctxloom.operators import cluster as K
from ctxloom.operators import coder as Z
from ctxloom.operators import counts as C
from ctxloom.operators import rates as R
from ctxloom.operators.contexts import Previous
from ctxloom.plans import streams as T
from ctxloom.plans import workloads as W

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def folder(spark, path, texts, links=()):
    """A folder of tables: documents of (doc_id, text, lang), and links to those of the smallest size."""
    rows = [(i, t, lang, "s", len(t or "")) for i, t, lang in texts]
    spark.createDataFrame(rows, DOCS).write.parquet(f"{path}/documents.parquet")
    for name in links:
        (path / f"{name}.parquet").symlink_to(f"/root/testdata/sf0.001/{name}.parquet")
    return str(path)


def test_round_trip_codes_every_symbol(spark, tmp_path, monkeypatch):
    sf = folder(spark, tmp_path, [(1, "ab c1 " * 50, "en"), (20, "x" * 50, "en"), (None, "hello wor" * 11 + "ld", "en"), (3, None, "en"), (7, "tail 9", "en"), (7, "tail 9", "en")])
    got = W.w18_round_trip(spark, sf).first()
    assert (got.reads, got.wrong) == (3 + 1 + 1 + 2, 0)
    decode = Z.decode
    monkeypatch.setattr(Z, "decode", lambda *a: decode(*a).where("read_no < 2"))  # a decoder that loses a tail
    assert W.w18_round_trip(spark, sf).first().wrong == 1


def test_round_trip_compares_short_strings(spark, tmp_path, monkeypatch):
    sf = folder(spark, tmp_path, [(1, "ab c1 " * 50, "en"), (2, "tail 9", "en"), (2, "tail 8", "en")])
    seen, decode = [], Z.decode
    monkeypatch.setattr(Z, "decode", lambda *a: seen.append(decode(*a)) or seen[0])
    assert W.w18_round_trip(spark, sf).first()[:2] == (5, 0)
    assert dict(seen[0].dtypes)["syms"] == "string"  # not four bytes a symbol through the shuffle
    digits = T.class4(spark, sf).cut(101, "keep").frame(digits=True).collect()
    assert sorted(r.syms for r in digits) == sorted("".join(map(str, r.syms)) for r in T.class4(spark, sf).cut(101, "keep").frame().collect())


def test_soft_machine_reads_the_whole_stream(spark, tmp_path):
    sf = folder(spark, tmp_path, [(i, ("aeiou " if i % 2 else "bcd 1 ") * 5 * (1 + i), "en") for i in range(8)], ("conversations", "events"))
    got = W.w7_soft_machine(spark, sf).where("stream = 'class4'").first()
    assert got.order0_bpv == R.rate(C.count_windows(T.class4(spark, sf), Previous(0))).first().bpv


def test_menus_keep_files_without_a_name(spark):
    costs = spark.createDataFrame([(None, [3.0, 1.0], 2), (None, [4.0, 2.0], 2), ("a", [1.0, 5.0], 2)], "f string, bits array<double>, n int")
    for method in ("greedy", "exhaustive"):
        for size in (1, 2):
            menus = K.choose_menu(costs, "f", 2, size, method)
            assert {r.f: r.bits for r in menus.collect()} == {None: 3.0, "a": 1.0}
            assert K.menu_costs(costs, menus, "f").agg({"bits": "sum"}).first()[0] == 4.0


def test_library_is_trained_on_every_read(spark, tmp_path, monkeypatch):
    sf = folder(spark, tmp_path, [(i, "some words, and 1 more. " * 9, None if i % 2 else "en") for i in range(20)])
    trained = []
    train = K.train_library
    monkeypatch.setattr(K, "train_library", lambda *a, **o: trained.append(o.get("sample", 1.0)) or train(*a, **o))
    assert {r.reads for r in W.w13_library(spark, sf).collect()} == {20 * 3} and trained == [1.0]  # tails, too


def test_blocks_are_of_one_length_and_hold_every_symbol(spark, tmp_path):
    sf = folder(spark, tmp_path, [(i, "ab c1." * (1 + i), "en") for i in range(20)])  # 1,260 symbols
    assert [(r.block_no, len(r.syms)) for r in W.blocks_of(spark, sf, 500)[0].orderBy("block_no").collect()] == [(0, 500), (1, 500), (2, 260)]
    assert W.w11_adaptive_orders(spark, sf).where("ord = 0").first().n == 1260
    assert [(r.block_no, r.n) for r in W.w10_half_lives(spark, sf).collect()] == [(0, 630)]


def test_pages_are_read_to_their_end(spark, tmp_path):
    spark.createDataFrame([(i, "u", "<p>some page.</p> " * (4 + i)) for i in range(9)], "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    whole = sum(18 * (4 + i) for i in range(9))
    got = {r.context: r.n for r in W.position_rates_pages(spark, str(tmp_path)).collect()}
    assert got["position"] == got["coarse position"] == whole
    assert {r.reads for r in W.w3_position_bins(spark, str(tmp_path)).collect()} == {"all", "first read only"}


def test_consensus_groups_are_near_copies(spark, tmp_path):
    words = [f"word{chr(97 + i // 26)}{chr(97 + i % 26)}" for i in range(300)]
    text, opening = " ".join(words[:150]), "the same long opening line of many documents. "
    other = [opening + " ".join(words[a : a + 60]) for a in (160, 230)]
    sf = folder(spark, tmp_path, [(1, text, "en"), (2, "Another" + text, "en"), (3, other[0], "en"), (4, other[1], "en")])
    assert {r.method: r.n for r in W.w15_consensus(spark, sf).collect()}["consensus"] == 2 * len(text) + 7
