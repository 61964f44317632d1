"""The worked example, invariants and brute force for training, visibility, encoding and minimum tokens."""

import collections
import itertools
import os
import random

import pyarrow as pa
import pytest
import regex
from pyspark.sql import functions as F

from slotweave.functions import cleaning
from slotweave.functions.pretok import PYTHON, pretokenize
from slotweave.functions.symbols import symbol
from slotweave.operators import corpus, measures as ms
from slotweave.operators.encode import ChunkEncoder, decode_ids, encode, encode_chunks_native, encoded_length, in_parts, length_from_log, replay, vp_length_from_log, with_specials
from slotweave.operators.exposure import exposure_by_count, exposures
from slotweave.operators.mintoken import Trie, fewest, min_length, min_tokens, min_tokens_relational, segment, vocabulary
from slotweave.operators import train
from slotweave.operators.train import STRATEGIES, TrainingExhausted, advance, chunk_table, merged, train_bpe
from slotweave.operators.visibility import InsufficientCandidates, export_standard, prune_only, reallocate, reexport, required_slots, tau_from_ratio
from slotweave.plans import workloads
from slotweave.sources.bundles import load_checkpoint, load_tokenizer, save_checkpoint, save_tokenizer, uses_pretokenizer

EXAMPLE = [("abc", 4), ("bc", 2), ("abcd", 2), ("xy", 3)]


@pytest.fixture(scope="module")
def chunks(spark):
    return spark.createDataFrame(EXAMPLE, "sym string, n long").persist()


def test_worked_example(spark, chunks):
    log = train_bpe(chunks, 2, "compact")
    assert [(m.left, m.right, m.freq, m.repl) for m in log.merges] == [(98, 99, 8, 8), (97, 256, 6, 6)]
    tok, log = reallocate(chunks, log, 262, "0.40")
    assert tok.tau == 3 and tok.internal == {256} and len(tok.log) == 3
    assert [tok.export_ids()[t] for t in (257, 258, 256)] == [256, 257, 262]
    std = export_standard(log, 262)
    assert [length_from_log(log, m) for m in (0, 2, 3)] == [30, 16, 13]
    assert vp_length_from_log(tok, log) == 15 == encoded_length(chunks, tok)
    assert ms.decompose(tok, std, log) == (3, 2, 1)
    assert (min_length(chunks, vocabulary(std)), min_length(chunks, vocabulary(tok))) == (16, 15)
    with pytest.raises(InsufficientCandidates):
        reallocate(chunks, log, 262, "1")
    low, _ = reallocate(chunks, log, 262, "0.20")
    assert low.internal == frozenset() and low.log == std.log
    assert prune_only(log, 3, 262).n_visible == 261


@pytest.mark.parametrize("words", [EXAMPLE, [("aaaa", 3), ("aaaaa", 2), ("abab", 4)], [("abcabc", 2), ("cab", 5), ("bca", 5)]])
def test_strategies_agree(spark, words):
    c = spark.createDataFrame(words, "sym string, n long")
    logs = [train_bpe(c, 6, s) for s in STRATEGIES]
    assert all(log == logs[0] for log in logs)
    assert all(train_bpe(c, 6, s, logs[0].prefix(2)) == logs[0] for s in STRATEGIES)


def test_reallocation_above_the_compact_limit(spark, chunks, monkeypatch):
    want = reallocate(chunks, train_bpe(chunks, 2, "compact"), 262, "0.40")[0]
    monkeypatch.setattr(train, "COMPACT", 0)
    assert reallocate(chunks, train_bpe(chunks, 2), 262, "0.40")[0] == want


def test_advance_is_all_merges_in_order(spark, trained):
    c, log = trained
    few = log.prefix(40)
    assert advance(c, list(few.merges)).exceptAll(merged(c, few)).isEmpty()


@pytest.fixture(scope="module")
def trained(spark, sf):
    c = chunk_table(spark.read.parquet(f"{sf}/benchmark.parquet")).persist()
    return c, train_bpe(c, 120, "compact")


def test_exposure_and_lengths(spark, trained):
    c, log = trained
    short = log.prefix(20)
    counted = {r.token: r.exposure for r in exposure_by_count(c, short).collect()}
    assert counted == dict(enumerate(exposures(short)))
    assert encoded_length(c, export_standard(log, 260 + 20)) == length_from_log(log, 20)


def test_reallocation_invariants(spark, trained, sf):
    c, log = trained
    n = 260 + 60
    toks = [reallocate(c, log, n, r)[0] for r in ("0.2", "0.3", "0.4")]
    full = reallocate(c, log, n, "0.4")[1]
    for tok in toks:
        assert tok.n_visible == n and len(tok.log) == tok.trained
        ids = tok.export_ids()
        assert sorted(ids[t] for t in tok.visible) == list(range(n - 4))
        assert vp_length_from_log(tok, full) == encoded_length(c, tok)
        e = exposures(tok.log)
        assert all((e[m.token] >= tok.tau) == (m.token not in tok.internal) for m in tok.log.merges)
    assert toks[0].internal <= toks[1].internal <= toks[2].internal
    assert reallocate(c, log, n, tau=0)[0].log == export_standard(log, n).log
    wide, _ = reallocate(c, log, n, "0.4", batch=7)
    assert (wide.trained - 60) % 7 == 0 and wide.n_visible == n


def test_round_trip_and_bundle(spark, trained, sf, tmp_path):
    c, log = trained
    tok, _ = reallocate(c, log, 320, "0.4")
    docs = spark.createDataFrame([(1, "GPT-4 déjà vu, 1949年6月24日\r\n\tx  y"), (2, ""), (3, None), (4, "😀" * 50)], "doc_id long, text string")
    got = {r.doc_id: r.text for r in decode_ids(encode(docs, tok), tok).collect()}
    assert got == {1: docs.first().text, 2: "", 3: "", 4: "😀" * 50}
    ids = {i for r in encode(docs, tok).collect() for i in r.ids}
    assert max(ids) < len(tok.visible)
    save_tokenizer(tok, str(tmp_path / "tok"), spark)
    assert load_tokenizer(spark, str(tmp_path / "tok")) == tok
    save_checkpoint(c, log.prefix(30), str(tmp_path / "ck"))
    again, part = load_checkpoint(spark, str(tmp_path / "ck"))
    assert train_bpe(again, 120, "compact", part) == log


def test_minimum_tokens(spark, trained):
    c, log = trained
    tok = export_standard(log, 320)
    words = vocabulary(tok)
    few = c.filter(F.char_length("sym") <= 9).limit(60).persist()
    a, b = min_tokens(few, words), min_tokens_relational(few, words)
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()
    trie, known, one = Trie(words), set(words), ChunkEncoder(tok)
    for r in few.limit(25).collect():
        data = bytes(map(ord, r.sym))
        best = min(k + 1 for k in range(len(data)) for cut in itertools.combinations(range(1, len(data)), k) if all(data[i:j] in known for i, j in zip((0, *cut), (*cut, len(data)), strict=True)))
        assert len(segment(trie, data)) == best <= len(one.tokens(data))


CUTS = {
    "a b": ["a", " b"], "a  b": ["a", "  ", "b"], "x\n\ty": ["x", "\n", "\t", "y"], "user_id": ["user_id"], "déjà": ["déjà"], "don't": ["don't"], "GPT-4": ["GPT-4"], "Node.js": ["Node.js"],
    "C++": ["C++"], "3.14": ["3.14"], "10-20": ["10-20"], "123abc": ["123", "abc"], "1949年6月24日": ["1949", "年", "6", "月", "24", "日"], "a,b": ["a", ",", "b"], "...": ["..."], "))": ["))"],
    "</div>": ["</", "div", ">"], "": [], " ": [" "], ".py": [".py"], "abc123": ["abc123"], "x.pyramid": ["x", ".", "pyramid"], "app.jsonl": ["app", ".", "jsonl"], "a.python": ["a", ".", "python"],
    "app.json, x.js.": ["app.json", ",", " x.js", "."], "C'était": ["C'était"], "IPv6": ["IPv6"], "GPT4": ["GPT4"], "COVID-19": ["COVID-19"], "file.java": ["file.java"], "C#": ["C#"], "Montréal": ["Montréal"], "---": ["---"], "===": ["==="],
    "ひらがな3カタカナ": ["ひらがな", "3", "カタカナ"], "한글12 Seoul": ["한글", "12", " Seoul"], "x\t\ty": ["x", "\t\t", "y"], " 漢字": [" 漢字"], "привет мир": ["привет", " мир"], ".pyx": [".", "pyx"],
}


def test_pretokenizer(spark):
    rows = spark.createDataFrame(list(CUTS.items()), "t string, want array<string>").withColumn("got", pretokenize(F.col("t"))).collect()
    assert [r.t for r in rows if r.got != r.want] == []
    grammar = regex.compile(PYTHON)
    assert all([m.group() for m in grammar.finditer(t)] == want for t, want in CUTS.items())


LONG_RUNS = {
    "han": "\u6f22" * 1_000_000, "han and marks": "\u6f22\u0301" * 500_000, "marks": "\u0301" * 200_000, "numbers": "1." * 500_000, "dates": "1-" * 500_000, "apostrophes": "a'" * 500_000, "latin": "e" * 1_000_000,
    "latin and marks": "e\u0301" * 500_000, "underscores": "_" * 1_000_000, "spaces": " " * 1_000_000, "extensions": "a.py" * 250_000, "dots": "." * 1_000_000, "all": "a'1.\u6f22 -_\u0301" * 100_000,
}


def test_pretokenizer_on_long_runs(spark):
    rows = spark.createDataFrame(list(LONG_RUNS.items()), "name string, t string").repartition(4)
    got = rows.select("name", F.array_join(pretokenize(F.col("t")), "") == F.col("t"), F.size(pretokenize(F.col("t")))).collect()
    assert all(r[1] for r in got)
    sizes = {r[0]: r[2] for r in got}
    assert sizes["han"] == sizes["han and marks"] == sizes["latin"] == sizes["dots"] == sizes["spaces"] == 1 and sizes["numbers"] == 2


def test_without_the_pretokenizer(spark):
    docs = spark.createDataFrame([("a b a b",), ("",), (None,), ("a b a b",)], "text string")
    c = chunk_table(docs, pretok=False)
    assert [(r.sym, r.n) for r in c.collect()] == [("a b a b", 2)]
    log = train_bpe(c, 2, "compact")
    assert any(b" " in m.bytes for m in log.merges)
    tok = export_standard(log, 262)
    ids = encode(docs.withColumn("doc_id", F.lit(1)), tok, pretok=False).collect()
    assert sorted(len(r.ids) for r in ids) == sorted([length_from_log(log) // 2] * 2 + [0, 0])


def test_slots_and_threshold():
    assert required_slots(260) == 0
    with pytest.raises(ValueError):
        required_slots(259)


def test_decimal_ceiling(spark):
    c = spark.createDataFrame([("ab", 100)], "sym string, n long")
    assert tau_from_ratio(train_bpe(c, 1, "compact"), 1, "0.07") == 7


def test_queries_have_keys():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())


def test_files(spark, tmp_path):
    from slotweave.sources import tables

    docs = spark.createDataFrame([(1, 'a "b"\nc, d', "en", "s", 3), (2, "déjà", "fr", "s", 4)], tables.DOCUMENTS)
    for kind in ("parquet", "json", "csv", "orc"):
        tables.write(docs, str(tmp_path / kind), kind)
        assert sorted(tables.read(spark, str(tmp_path / kind), kind).collect()) == sorted(docs.collect())
    (tmp_path / "x.txt").write_bytes("é\nb".encode())
    assert [r.text for r in tables.read_texts(spark, str(tmp_path / "x.txt")).collect()] == ["é", "b"]
    assert tables.read_binary(spark, str(tmp_path / "x.txt")).first().sym == "Ã©\nb"


def test_sql_names(spark, trained):
    from slotweave.functions.udfs import register

    c, log = trained
    tok, _ = reallocate(c, log, 320, "0.4")
    register(spark, tok)
    row = spark.sql("SELECT size(tok_encode('hello')) AS a, tok_min_count('hello') AS b, tok_pretokenize('a  b') AS c").first()
    assert row.b <= row.a and row.c == ["a", "  ", "b"]
    text = "déjà vu, a  b\r\n1949年6月24日"
    assert [(r.pos, r.chunk) for r in spark.sql(f"SELECT * FROM tok_chunks('{text}')").collect()] == list(enumerate(spark.sql(f"SELECT tok_pretokenize('{text}') AS c").first().c))
    assert spark.sql(f"SELECT tok_decode(tok_encode('{text}')) AS t").first().t == text
    row = spark.sql("SELECT size(tok_min_segment('hello')) AS n, tok_min_count('hello') AS m").first()
    assert row.n == row.m
    seen = spark.sql("SELECT tok_exposure(c) AS e FROM VALUES ('hello'), ('hello'), (' the') v(c)").first().e
    one = ChunkEncoder(tok)
    assert seen == dict(collections.Counter(one("hello") * 2 + one(" the")))
    one = min(tok.internal) if tok.internal else 256
    assert [r.token for r in spark.sql(f"SELECT * FROM tok_expand({one})").collect()] == tok.expansions()[one]


def test_sessions_equal_batch(spark, sf):
    from slotweave.streaming import streams

    stream = streams.run_to_end(streams.sessions(streams.table_stream(spark, sf, "events")))
    batch = streams.sessions(spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")))
    assert stream.exceptAll(batch).isEmpty()


def test_long_chunks_merge_as_short_ones(spark, trained, monkeypatch):
    ranks = {(m.left, m.right): m.token for m in trained[1].merges}
    rng = random.Random(5)
    words = [[rng.choice(b"aetn o") for _ in range(rng.randrange(1, 90))] for _ in range(200)] + [[97] * 50, [97], []]
    want = [(train.merge_word(w, ranks, c := collections.Counter()), c) for w in words]
    monkeypatch.setattr(train, "LONG", 0)
    assert [(train.merge_word(w, ranks, c := collections.Counter()), c) for w in words] == want


def test_stream_of_ids(spark, trained, sf, tmp_path):
    from slotweave.streaming import streams

    tok, _ = reallocate(trained[0], trained[1], 320, "0.4")
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for _ in range(2):  # the second start finds nothing new
        q = streams.encode_to_folder(streams.table_stream(spark, sf, "documents"), tok, str(tmp_path / "ids"), str(tmp_path / "ck"))
        q.awaitTermination()
    got = spark.read.parquet(str(tmp_path / "ids")).select("doc_id", "ids")
    want = encode(docs, tok)
    assert got.count() == want.count() and got.exceptAll(want).isEmpty()
    shares = streams.drift(streams.running_exposure(spark.read.parquet(f"{sf}/benchmark.parquet"), tok, "item_id"), tok).collect()
    assert len(shares) == len(tok.visible) and all(abs(r.share - r.trained_share) < 1e-12 for r in shares)


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    from slotweave.streaming import streams

    day = "2024-01-0{} 00:00:00"  # rows count as late against the watermark of the micro-batch before
    for i, ts in enumerate((day.format(1), day.format(5), day.format(6), day.format(1), day.format(9))):
        spark.createDataFrame([(ts, "x")], "ts string, event_type string").selectExpr("CAST(ts AS timestamp) AS ts", "event_type").coalesce(1).write.mode("append").parquet(str(tmp_path / f"in{i}"))
        (tmp_path / "in").mkdir(exist_ok=True)
        part = next((tmp_path / f"in{i}").glob("*.parquet"))
        target = tmp_path / "in" / f"{i}.parquet"
        part.rename(target)
        os.utime(target, (1_700_000_000 + i, 1_700_000_000 + i))
    stream = spark.readStream.schema("ts timestamp, event_type string").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    q = streams.tumbling(stream).writeStream.outputMode("append").format("memory").queryName("late").trigger(availableNow=True).start()
    q.awaitTermination()
    assert streams.dropped_as_late(q) == 1
    assert spark.table("late").agg(F.sum("n")).first()[0] == 3  # the last day's window stays open


def test_bound_on_training(spark, chunks):
    log = train_bpe(chunks, 2, "compact")
    with pytest.raises(InsufficientCandidates):  # the third merge would be needed
        reallocate(chunks, log, 262, "0.40", n_max=258)
    assert reallocate(chunks, log, 262, "0.40", n_max=259)[0].internal == {256}
    with pytest.raises(TrainingExhausted):
        export_standard(log, 400)
    with pytest.raises(TrainingExhausted):
        reallocate(chunks, log, 400, "0.1")
    assert len(train_bpe(chunks, 500, "compact")) < 500


def test_reexport_needs_no_training(spark, trained):
    c, log = trained
    n = 260 + 60
    tok, longer = reallocate(c, log, n, "0.4")
    own = tok.log
    assert reexport(own, exposures(own), tok.tau, n) == tok
    with pytest.raises(InsufficientCandidates):
        reexport(own, exposures(own), 10**9, n)


def test_replay_is_the_encoded_length_on_all_pairs(spark, sf):
    items = spark.read.parquet(f"{sf}/benchmark.parquet")
    parts = {"A": items.filter("item_id % 2 = 0"), "B": items.filter("item_id % 2 = 1"), "AB": items}
    tables = {k: chunk_table(v).persist() for k, v in parts.items()}
    for a in parts:
        log = train_bpe(tables[a], 90, "compact")
        tok, log = reallocate(tables[a], log, 260 + 64, "0.5")
        for b in parts:
            on = replay(log, tables[b])
            assert vp_length_from_log(tok, on) == encoded_length(tables[b], tok)
            assert length_from_log(on, 64) == encoded_length(tables[b], export_standard(log, 260 + 64))
            if a == b:
                assert [m.repl for m in on.merges] == [m.repl for m in log.merges]


def test_specials_around_ids(spark, trained):
    tok = export_standard(trained[1], 300)
    df = spark.createDataFrame([([1, 2],), ([],)], "ids array<int>")
    first = len(tok.visible)
    got = [r[0] for r in df.select(with_specials(F.col("ids"), tok, start=True, pad_to=6)).collect()]
    assert got == [[first + 1, 1, 2, first, first + 3, first + 3], [first + 1, first, first + 3, first + 3, first + 3, first + 3]]
    assert [r[0] for r in df.select(with_specials(F.col("ids"), tok, end=False)).collect()] == [[1, 2], []]
    back = decode_ids(spark.createDataFrame([(1, got[0])], "doc_id long, ids array<int>"), tok).first().text
    assert back.encode() == bytes([1, 2])


def test_ties_take_the_longest_first_word():
    words = [b"a", b"b", b"c", b"ab", b"bc"]
    assert segment(Trie(words), b"abc") == [3, 2]
    assert [fewest(Trie(words), w) for w in (b"", b"a", b"abc", b"abcbc")] == [0, 1, 2, 3]


def test_chains_end_at_visible_tokens(spark, trained):
    c, log = trained
    tok, _ = reallocate(c, log, 320, "0.8")
    assert tok.internal
    counts = {t: (direct, above) for t, direct, above in ms.support(tok)}
    for t, parents, chain in ms.chains(tok):
        assert len(parents) == counts[t][0] and bool(chain) == bool(counts[t][1])
        assert all(x in tok.internal for x in chain[:-1]) and not (chain and chain[-1] in tok.internal)
        assert all(tok.log.token_bytes(a) in tok.log.token_bytes(b) for a, b in zip([t, *chain], chain, strict=False))
        assert len(chain) == 1 if parents else len(chain) != 1


def test_bundle_records_the_pretokenizer(spark, trained, tmp_path):
    tok = export_standard(trained[1], 300)
    for pretok in (True, False):
        save_tokenizer(tok, str(tmp_path / str(pretok)), spark, pretok)
        assert uses_pretokenizer(spark, str(tmp_path / str(pretok))) == pretok and load_tokenizer(spark, str(tmp_path / str(pretok))) == tok


def test_training_keeps_one_table_and_frees_it(spark, chunks, tmp_path, monkeypatch):
    seen, roots = [], set()
    old = train._Cuts.__call__

    def counted(self, c):
        out = old(self, c)
        roots.add(self.root.removeprefix("file:"))
        seen.append(sum(not f.startswith(".") for f in os.listdir(self.root.removeprefix("file:"))))
        return out

    monkeypatch.setattr(train._Cuts, "__call__", counted)
    train_bpe(chunks, 3, "batch")
    assert seen and set(seen) == {1} and not any(os.path.exists(r) for r in roots)


def test_long_logs_count_like_the_closed_form(spark, trained):
    c, log = trained
    assert len(log) > train.NESTED
    assert {r.token: r.exposure for r in exposure_by_count(c, log).collect()} == dict(enumerate(exposures(log)))
    tok, more = reallocate(c, log, 320, "0.6")
    assert encode_chunks_native(c, tok).agg(F.sum(F.col("n") * F.col("tokens"))).first()[0] == encoded_length(c, tok)


def test_budgets_follow_the_size():
    sizes = [0, 10**5, 10**6, 10**7, 640 * 10**6, 10**14]
    tops = [workloads.budgets_for(n)[-1] for n in sizes]
    assert tops == sorted(tops) and tops[0] >= 320 and 15_000 < tops[4] <= 20_000 == tops[5]
    assert all(len(set(b - a for a, b in zip(x, x[1:], strict=False))) == 1 for x in map(workloads.budgets_for, sizes))


def test_cleaning_changes_no_character(spark):
    kept = ["ÀÉ ſt ﬁ Ａ\u00a0x", "É vs É", "tab\tline\nend\r\n", "ß SS ı İ", "漢字 ｶﾅ"]
    df = spark.createDataFrame([(x,) for x in kept], "text string")
    assert [r[0] for r in df.select(cleaning.strip_artifacts(F.col("text"))).collect()] == kept
    assert [r[0] for r in df.select(cleaning.drop_repeated_lines(F.col("text"))).collect()] == kept
    assert [r[0] for r in df.select(cleaning.strip_markup(F.col("text"))).collect()] == kept


def test_shards_are_one_corpus(spark, trained, tmp_path):
    docs = spark.createDataFrame([(i, f"text {i % 7} of many", "A" if i % 2 else "B") for i in range(40)], "doc_id long, text string, corpus string")
    for k in range(3):
        docs.filter(F.col("doc_id") % 3 == k).write.parquet(str(tmp_path / f"s{k}"))
    whole = corpus.read_shards(spark, [str(tmp_path / f"s{k}") for k in range(3)])
    assert chunk_table(whole).exceptAll(chunk_table(docs)).isEmpty() and whole.count() == 40
    tok = export_standard(trained[1], 300)
    from slotweave.sources.tables import write_ids

    write_ids(encode(docs, tok).join(docs.select("doc_id", "corpus"), "doc_id"), str(tmp_path / "ids"))
    back = spark.read.parquet(str(tmp_path / "ids"))
    assert back.count() == 40 and len(os.listdir(tmp_path / "ids")) >= 2


def test_token_kinds_and_balance(spark, trained):
    kinds = {b"\xe6": "partial_utf8", b" \n": "whitespace", b"</": "markup", b"the": "latin_fragment", "é".encode(): "latin_fragment", "漢".encode(): "other_script", b"!": "other"}
    assert {k: ms.token_class(k) for k in kinds} == kinds
    x = sorted(exposures(trained[1])[256:])
    brute = sum(abs(a - b) for a in x for b in x) / (2 * len(x) * sum(x))
    assert abs(ms.usage_balance(export_standard(trained[1], 260 + len(trained[1]))) - brute) < 1e-9


def test_domain_export_trains_until_no_pair_is_left(spark, sf, monkeypatch):
    rounds = []

    def far_enough(log, tau, need, batch=1):
        rounds.append(len(log))
        return None

    short = workloads.Study.of_folder(spark, sf)
    need = required_slots(short.budgets[0])
    full = train_bpe(short.chunks("AB"), need + 8)
    short._logs["AB"] = full.prefix(need)
    monkeypatch.setattr(workloads, "trained_far_enough", far_enough)
    monkeypatch.setattr(workloads, "train_bpe", lambda chunks, n, resume: full.prefix(min(len(resume) + 1, len(full))))
    with pytest.raises(InsufficientCandidates):
        workloads.w13_domain_export(short)
    assert rounds == list(range(need, need + 9))
    short.close()


def test_vocabulary_source(spark, trained, tmp_path):
    from slotweave.sources.vocabulary import read_vocabulary

    tok = export_standard(trained[1], 300)
    save_tokenizer(tok, str(tmp_path / "tok"), spark)
    want = [bytes(r.bytes) for r in tok.frame(spark).filter("visible").orderBy("export_id").collect()]
    for path in (str(tmp_path / "tok" / "visible"), f"file://{tmp_path}/tok/visible"):
        got = read_vocabulary(spark, path).orderBy("line").collect()
        assert [bytes(r.token) for r in got] == want and [r.line for r in got] == list(range(300))
    assert read_vocabulary(spark, str(tmp_path / "tok" / "internal")).count() == 0

    (tmp_path / "two").mkdir()
    (tmp_path / "two" / "a").write_text("61\n6162")
    (tmp_path / "two" / "b").write_text("63\n")
    (tmp_path / "two" / "_SUCCESS").write_text("no hex")
    assert sorted((r.file, r.line, bytes(r.token)) for r in read_vocabulary(spark, str(tmp_path / "two")).collect()) == [("a", 0, b"a"), ("a", 1, b"ab"), ("b", 0, b"c")]
    assert read_vocabulary(spark, str(tmp_path / "two" / "a")).count() == 2
    (tmp_path / "two" / "b").write_text("zz\n")
    with pytest.raises(Exception, match="hex"):
        read_vocabulary(spark, str(tmp_path / "two")).collect()
    with pytest.raises(Exception, match="absent"):
        read_vocabulary(spark, str(tmp_path / "absent")).collect()


def test_rate_source_and_console_sink(spark):
    import time

    from slotweave.streaming import streams

    query = streams.to_console(streams.tumbling(streams.rate_events(spark, 50), "1 second"), "update")
    try:
        end = time.time() + 60
        while time.time() < end and not any(p["numInputRows"] for p in query.recentProgress):
            time.sleep(0.5)
        assert query.exception() is None and any(p["numInputRows"] for p in query.recentProgress)
    finally:
        query.stop()
    types = streams.rate_events(spark, 50)
    assert types.isStreaming and types.columns == ["event_id", "ts", "event_type"]


def test_runs_of_frequent_pairs_train_alike(spark, sf, monkeypatch):
    c = chunk_table(spark.read.parquet(f"{sf}/benchmark.parquet")).persist()
    want = train_bpe(c, 400, "compact")
    monkeypatch.setattr(train, "COMPACT_SYMBOLS", 4_000)
    monkeypatch.setattr(train, "PAIRS", 16)
    passes, alone = [], train._in_one_task

    def told(pieces, *rest):
        passes.append(pieces.agg(F.sum(F.char_length("sym"))).first()[0])
        return alone(pieces, *rest)

    monkeypatch.setattr(train, "_in_one_task", told)
    assert train_bpe(c, 400) == want and train_bpe(c, 400, "runs", want.prefix(150)) == want
    assert len(passes) > 4 and max(passes) <= 4_000


def test_runs_with_repeats_and_ties(spark):
    texts = ["aaaaaaa", "aaabaaab", "ababababa", "aa", "xyxyx", "zz", "qwer", "tyui", "aaaa aaaa"]
    c = chunk_table(spark.createDataFrame([(i, x) for i, x in enumerate(texts)], "doc_id long, text string"), pretok=False).persist()
    for n in (1, 3, 12, 200):
        assert train_bpe(c, n, "runs") == train_bpe(c, n, "compact")


def test_no_streamed_row_stays_on_the_driver(spark, sf, tmp_path, monkeypatch):
    from slotweave.streaming import streams

    monkeypatch.setattr(streams, "shared_folder", lambda _: (str(tmp_path), None))
    got = streams.run_to_end(streams.deduplicated(streams.table_stream(spark, sf, "events")))
    assert got.inputFiles() and all(str(tmp_path) in f for f in got.inputFiles()) and got.count() == spark.read.parquet(f"{sf}/events.parquet").count()
    assert not list(tmp_path.glob("*/checkpoint"))


def test_streamed_join_is_on_files(spark, sf):
    from slotweave.plans.queries import queries

    got = queries()["op_st_join"](spark, sf)
    events, customers = (spark.read.parquet(f"{sf}/{x}.parquet") for x in ("events", "customer"))
    assert got.inputFiles() and got.exceptAll(events.join(customers, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment")).isEmpty()


def test_large_trainings_send_the_driver_no_more_pairs_than_a_pass_takes(spark, trained, monkeypatch):
    monkeypatch.setattr(train, "PAIRS", 4)
    monkeypatch.setattr(train, "top_pairs", None)  # sends up to so many pairs from every partition
    chunks = trained[0].repartition(7)
    assert train.train_bpe(chunks, 40, "runs") == train.train_bpe(chunks, 40, "compact")
    pairs = train.pair_counts(chunks)
    every = sorted((-r.f, r.pair) for r in pairs.collect())
    for width in (1, 5, 50, len(every) - 1, len(every)):
        top, counted = train.frequent(pairs, width)
        want = [x for x in every if width == len(every) or x[0] < every[width][0]]
        assert top == want and sum(n for _, n in counted) >= min(width + 1, len(every))


@pytest.mark.parametrize("name", ["op_st_join", "op_st_sessions"])
def test_streams_read_tables_that_are_folders(spark, sf, tmp_path, name):
    from slotweave.plans.queries import queries

    for table in ("events", "customer"):
        spark.read.parquet(f"{sf}/{table}.parquet").repartition(3).write.parquet(str(tmp_path / f"{table}.parquet"))
    got, want = queries()[name](spark, str(tmp_path)), queries()[name](spark, sf)
    assert not want.isEmpty() and got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()


def test_complete_mode_is_its_last_batch_on_files(spark, sf, tmp_path):
    from slotweave.streaming import streams

    events = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    for i in range(2):
        events.filter(F.col("event_id") % 2 == i).coalesce(1).write.parquet(str(tmp_path / f"in/{i}"))
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in/*"))
    got = streams.run_to_end(streams.sessions(stream), "complete")
    want = streams.sessions(events)
    assert got.inputFiles() and got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()


def test_recursion_goes_as_far_as_the_keys(spark, sf):
    from slotweave.plans.queries import queries

    rows = sorted(map(tuple, queries()["op_s50_recursive"](spark, sf).collect()))
    keys = [r.c_custkey for r in spark.read.parquet(f"{sf}/customer.parquet").collect()]
    assert rows == [(k.bit_length(), 1 << (k.bit_length() - 1), sum(x.bit_length() == k.bit_length() for x in keys)) for k in (1 << i for i in range(max(keys).bit_length()))]



def test_fixtures_are_cut_before_each_document(spark, sf):
    from slotweave.plans.queries import FIXTURES, queries

    got, docs = queries()["pretok_fixtures"](spark, sf), spark.read.parquet(f"{sf}/documents.parquet")
    assert got.inputFiles() == docs.inputFiles() and got.count() == docs.count() and got.select("fixture").distinct().count() == min(len(FIXTURES), docs.count())


def test_merges_of_strings_are_those_of_words(trained):
    ranks = {(m.left, m.right): m.token for m in trained[1].merges}
    rng = random.Random(6)
    words = [[rng.choice(b"aetn o") for _ in range(rng.randrange(1, 2 * train.LONG))] for _ in range(200)] + [[97] * 50, [97], []]
    after, text = train.Replacer(ranks), lambda word: "".join(map(symbol, word))
    for w in words:
        want, made = collections.Counter(), collections.Counter()
        assert after(text(w), made) == text(train.merge_word(w, ranks, want)) and made == want


def test_encoding_holds_a_bounded_number_of_chunks():
    rows = [[("a " * n).split() for n in sizes] for sizes in ((3, 0, 4, 9, 1, 1), (), (0,), (20,))]
    for r in rows:
        batch = pa.RecordBatch.from_arrays([pa.array(range(len(r)), pa.int64()), pa.array([x or None for x in r], pa.list_(pa.string()))], names=["id", "c"])
        parts = list(in_parts(batch, 5))
        assert [x for p in parts for x in p.to_pylist()] == batch.to_pylist()
        assert all(p.num_rows <= 1 or sum(len(c or ()) for c in p.column(1).to_pylist()) <= 5 for p in parts)


def test_minimum_tokens_of_a_union_are_the_sums_of_its_parts(spark, sf, monkeypatch):
    items = spark.read.parquet(f"{sf}/benchmark.parquet")
    part = {"A": items.filter("item_id % 2 = 0"), "B": items.filter("item_id % 2 = 1"), "AB": items}
    s = workloads.Study(spark, lambda name: chunk_table(part[name]), [300, 310], ["0.4"])
    passes, whole = [], min_length(s.chunks("AB"), vocabulary(s.tokenizer("AB", 300)))
    monkeypatch.setattr(workloads, "min_lengths", lambda chunks, words, real=workloads.min_lengths: passes.append(chunks) or real(chunks, words))
    got = {r.eval: r.len_std for r in workloads.w08_minimum_tokens(s).collect()}
    assert got["A"] + got["B"] == got["AB"] == whole and len(passes) == 2
    s.close()
