"""op1, op2, op4, op6 and op7: extraction, scoring, leaks, exact round trips of ids; and the pipeline's stages."""

import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from tokenizers import Tokenizer

import corpus_pipeline
from kgfold.llm import toxicity
from kgfold.llm.common import staged, table
from kgfold.llm.decontaminate import ItemIndex, find_leaks, words_of
from kgfold.llm.html_paths import extract, main_text
from kgfold.llm.id_store import read_checks, read_documents, shifted_crc, write_store
from kgfold.llm.packing import pack
from kgfold.llm.token_units import UnitEncoder

ARTICLE = "<article><h1>On &amp; off</h1><p>First long paragraph, with words, and more words.<p>Second one\n  has <b>bold</b> text; it is long enough, too.</p><p>End.</p></article>"


def test_main_text():
    page = f"<html><head><title>t</title><style>p{{}}</style><script>var a='</p><p>no</p>';</script></head><body><header><a href=/>Home</a></header><nav><ul><li><a href='/x'>x</a></ul></nav><div class='cookie-notice'>We use cookies, yes.</div>{ARTICLE}<aside>More, to read, here.</aside><div id=comments><p>A comment, quite long, and another clause, by a reader.</p></div><form>Mail <input></form><footer>&copy; us</footer>"
    assert main_text(page) == "On & off\nFirst long paragraph, with words, and more words.\nSecond one has bold text; it is long enough, too.\nEnd."
    assert main_text(page.replace("<article>", "<div class=body>").replace("</article>", "</div>")) == main_text(page)
    assert main_text(None) == main_text("") == main_text("<nav>x</nav>") == ""
    assert main_text("<p>cut off &am") == "cut off &am" and main_text("<p>open <b tag") == "open"


def test_extract(spark, sf_dir):
    rows = extract(table(spark, sf_dir, "pages").unionByName(spark.createDataFrame([(-1, None, None)], "page_id long, url string, html string"))).collect()
    assert len(rows) == 51 and all(r["n_chars"] == len(r["text"]) for r in rows) and all(r["text"] for r in rows if r["page_id"] >= 0)


def test_automata():
    lexicon = toxicity.FuzzyLexicon({"idiot": 1.0, "stupid": 1.0, "lowei*": 1.0, "disgusting": 1.0})
    hit = lambda w: (lambda m: m and (m[0], lexicon.weights[m[1]][0]))(lexicon.match(w))
    assert hit("idiot") == (0, "idiot") and hit("idot") == hit("idiott") == hit("idiom") == (1, "idiot")
    assert hit("loweischaft") == (0, "lowei*") and hit("lowe") is None and hit("clean") is None
    assert hit("disgstig") == (2, "disgusting") and hit("dsgstig") is None


def test_toxicity(spark):
    docs, labels = (table(spark, "/root/testdata/sf0.01", t) for t in ("documents", "labels"))
    scored = toxicity.score(docs, toxicity.train(docs, labels)).join(labels, "doc_id").toPandas()
    assert (scored.predicted == scored.toxic)[scored.held_out].mean() > 0.95
    assert ((scored.predicted == 1) & (scored.toxic == 0)).sum() <= 2
    none = toxicity.Scorer(toxicity.FuzzyLexicon({}))
    assert none.score(None) == none.score("") < 0.5
    assert toxicity.train(docs, labels.limit(0)).lexicon.weights == []


def test_quotation_counts_less():
    lexicon = toxicity.FuzzyLexicon({"idiot": 3.0})
    plain, quoted = (toxicity.Scorer(lexicon).score(t) for t in ("you are an idiot and you know it", 'the word "idiot" is an insult in this text'))
    assert quoted < plain


@pytest.mark.parametrize("dense", [True, False])
def test_leaks(spark, sf_dir, dense):
    docs, items = table(spark, sf_dir, "documents").collect(), table(spark, sf_dir, "benchmark").collect()
    index = ItemIndex([(r["item_id"], r["text"]) for r in items])
    if not dense:
        index.table = None
    want = {(d["doc_id"], i["item_id"]) for d in docs for i in items if i["text"] in d["text"]}
    got = {(d["doc_id"], h[0]) for d in docs for h in index.hits(d["text"], 0.45, 0.5)}
    assert want and got == want


def test_leaks_with_one_changed_word(spark, sf_dir):
    items = [(r["item_id"], r["text"]) for r in table(spark, sf_dir, "benchmark").collect()]
    index = ItemIndex(items)
    frame = "some plain words that stand before and after the passage".split()
    for item_id, text in items:
        words = words_of(text)
        for at in range(len(words)):
            edited = [*frame, *words[:at], "zzyzx", *words[at + 1 :], *frame]
            assert item_id in {h[0] for h in index.hits(" ".join(edited), 0.45, 0.5)}, (item_id, at)


def test_leaks_in_shards_and_empty_tables(spark, sf_dir):
    docs, items = table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")
    a, b = (sorted((r["doc_id"], r["item_id"]) for r in find_leaks(docs, items, shard_items=n).collect()) for n in (7, 20_000))
    assert a == b
    assert find_leaks(docs, items.limit(0)).collect() == find_leaks(docs.limit(0), items).collect() == []


TEXTS = ["", "Hello  world\n\n new\tline", "ÀÉ ﬁ 12345 it's   ", " lead", "a b c", "<|endoftext|> x  <|endoftext|>", "\x1c odd \x85 white\r\n", "日本語 テキスト"]


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "byte_bpe_50k.json"])
def test_units_give_the_same_ids(spark, sf_dir, name):
    texts = TEXTS + [r["text"] for r in table(spark, sf_dir, "documents").collect()]
    plain, fast = Tokenizer.from_file(public_tokenizers.path(name)), UnitEncoder(public_tokenizers.path(name))
    assert fast.units is not None
    for text, ids in zip(texts, fast.encode(texts), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == plain.encode(text, add_special_tokens=False).ids


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "byte_bpe_50k.json"])
def test_only_new_pieces_reach_the_tokenizer(name):
    path = public_tokenizers.path(name)
    plain, fast, asked = Tokenizer.from_file(path), UnitEncoder(path), []
    whole = fast._whole
    fast._whole = lambda texts: asked.extend(texts) or whole(texts)
    fast.encode(["alpha beta"])
    asked.clear()
    fast.encode(["alpha, beta!9"])
    assert asked and not any("alpha" in a or "beta" in a for a in asked)
    rng = np.random.default_rng(1)
    letters = list("aBz'sStTreveLLmMd09 \n\t\r\x0b\x0c\x1c\x1f\x00.,!-_\"é\u0301 Σ²İ")
    texts = ["".join(rng.choice(letters, rng.integers(0, 60))) for _ in range(3000)]
    for text, ids in zip(texts, fast.encode(texts), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == plain.encode(text, add_special_tokens=False).ids


def test_full_cache_keeps_its_older_half_and_the_ids(spark, sf_dir):
    path = public_tokenizers.path("byte_bpe_50k.json")
    texts = [r["text"] or "" for r in table(spark, sf_dir, "documents", "text").limit(60).collect()]
    roomy, tight = UnitEncoder(path), UnitEncoder(path, max_units=200)
    for a in range(0, len(texts), 5):
        first = list(tight.cache)[:100]
        assert tight.encode(texts[a : a + 5]) == roomy.encode(texts[a : a + 5])
        assert list(tight.cache)[:100][: len(first)] == first
    assert len(tight.cache) < len(roomy.cache)


def test_shifted_crc():
    a, b = b"some ids", b"and some more ids, at length"
    parts = shifted_crc(np.array([zlib.crc32(a), zlib.crc32(b)], np.uint32), np.array([len(b), 0]))
    assert int(parts[0] ^ parts[1]) == zlib.crc32(a + b)


def docs_and_ids(spark, sf_dir, name):
    rows = [(r["doc_id"], r["text"]) for r in table(spark, sf_dir, "documents").collect()] + [(10_000 + i, t) for i, t in enumerate([*TEXTS, None])]
    t = Tokenizer.from_file(public_tokenizers.path(name))
    return spark.createDataFrame(rows, "doc_id long, text string"), {i: [*t.encode(x or "", add_special_tokens=False).ids, 1] for i, x in rows}


def test_store_round_trip(spark, sf_dir, tmp_path):
    docs, ids = docs_and_ids(spark, sf_dir, "word_bpe_49k.json")
    folder = str(tmp_path / "store")
    write_store(docs.repartition(3), folder, public_tokenizers.path("word_bpe_49k.json"))
    at, checks = 0, sorted(read_checks(spark, folder).collect())
    assert [r["doc_id"] for r in checks] == sorted(ids)
    for r in checks:
        own = ids[r["doc_id"]]
        assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (at, len(own), zlib.crc32(np.array(own, "<u4").tobytes()))
        at += len(own)
    assert {r["doc_id"]: r["ids"] for r in read_documents(spark, folder).collect()} == ids


@pytest.mark.parametrize("loss", ["recipe file", "recipe row", "altered recipe", "lost chunk"])
def test_damaged_stores_are_refused(spark, sf_dir, tmp_path, loss):
    folder = tmp_path / "store"
    write_store(table(spark, sf_dir, "documents", "doc_id", "text").limit(60).repartition(3), str(folder), public_tokenizers.path("word_bpe_49k.json"))
    assert read_checks(spark, str(folder)).count() == read_documents(spark, str(folder)).count() == 60
    files = sorted((folder / ("packed/kind=c" if loss == "lost chunk" else "recipes")).glob("*.parquet"))
    path = next(f for f in files if pq.ParquetFile(f).metadata.num_rows > 1)
    rows = pq.ParquetFile(path).read()
    (path.parent / f".{path.name}.crc").unlink()
    path.unlink()
    if loss == "altered recipe":
        rows = rows.set_column(rows.schema.get_field_index("doc_id"), "doc_id", pa.array([-5, *rows.column("doc_id").to_pylist()[1:]], pa.int64()))
    if loss != "recipe file":
        pq.write_table(rows if loss == "altered recipe" else rows.slice(1), path)
    for read in (read_checks, read_documents):
        with pytest.raises(Exception, match="fit the manifest|lacks|missing"):
            read(spark, str(folder)).collect()


def test_packing_is_gapless_and_whole(spark, sf_dir):
    docs, ids = docs_and_ids(spark, sf_dir, "byte_bpe_50k.json")
    rows = pack(docs.repartition(5), public_tokenizers.path("byte_bpe_50k.json")).toPandas()
    for i, part in rows.sort_values(["doc_id", "start"]).groupby("doc_id"):
        at = 0
        for r in part.itertuples():
            assert r.start == at and r.ids_crc32 == zlib.crc32(np.array(ids[i][at : at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(ids[i]) == r.doc_tokens
    for _, part in rows.sort_values(["sequence_id", "offset"]).groupby("sequence_id"):
        assert (part.offset == part.length.cumsum().shift(fill_value=0)).all() and part.length.sum() <= 2048
    assert 1 - rows.length.sum() / (2048 * rows.sequence_id.nunique()) < 0.05
    assert pack(docs.limit(0), public_tokenizers.path("byte_bpe_50k.json")).collect() == []


def test_pipeline_stages(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    base = {r["doc_id"]: r["text"] for r in docs.collect()}
    items = [r["text"] for r in table(spark, sf_dir, "benchmark").collect()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = {r["doc_id"]: r["text"] for r in docs.collect()}
        docs = staged(stage(spark, docs, sf_dir), name)
        assert docs.columns == corpus_pipeline.COLUMNS
        after = {r["doc_id"]: r["text"] for r in docs.collect()}
        assert set(after) <= set(before)
        if name == "decontamination":
            assert set(before) - set(after) == {i for i, t in before.items() if any(x in t for x in items)}
        if name == "near_duplicates":
            from test_pairs import classes_of

            groups = classes_of(sorted(before.items()))
            assert set(after) == {i for i, (_, c) in groups.items() if c == i}
        if name == "personal_data":
            from test_spans import private_of

            assert set(after) == set(before)
            assert all(after[i] == t for i, t in before.items() if not private_of(t)) and not any(private_of(t) for t in after.values())
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, sf_dir)
    assert {r["doc_id"] for r in pieces.collect()} == {r["doc_id"] for r in docs.collect()} <= set(base)
