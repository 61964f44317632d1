"""One query for each method, measure and operator, with the SQL that says the same to another engine."""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from slotweave.functions import cleaning
from slotweave.functions.pretok import KINDS, RE2, chunk_kind, pretokenize
from slotweave.operators import corpus, measures as ms
from slotweave.operators.encode import decode_ids, encode, encode_chunks_native, encoded_length, length_from_log, vp_length_from_log, with_specials
from slotweave.operators.exposure import absorption, exposure_by_count, exposure_from_log, exposures
from slotweave.operators.mintoken import min_length, min_tokens, min_tokens_relational, vocabulary
from slotweave.operators.train import STRATEGIES, apply_merge, chunk_table, pair_counts, top_pairs, train_bpe
from slotweave.operators.visibility import InsufficientCandidates, export_standard, prune_only, reallocate, reexport, required_slots, tau_from_ratio
from slotweave.plans import workloads
from slotweave.sources.tables import over_all_cores
from slotweave.streaming import streams

#: Merges of the small training whose every step SQL repeats; learned slots of its exports, with which some tokens do turn internal; their visible size.
SMALL, SLOTS = 24, 64
VISIBLE = 256 + 4 + SLOTS

_Q: dict = {}
_O: dict = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        _Q[key] = f
        if sql:
            _O[key] = sql
        return f

    return add


def t(spark, sf, name):
    return spark.read.parquet(f"{sf}/{name}.parquet")


def texts(spark, sf, name):
    """A table for work on its texts: all cores take part, even if it is one small file."""
    return over_all_cores(t(spark, sf, name))


PATTERN = RE2.replace("'", "''")
CORPORA = """d AS (SELECT min(doc_id) AS doc_id, arg_min(lang, doc_id) AS lang, text FROM documents WHERE text IS NOT NULL GROUP BY text),
    corpora AS (SELECT *, CASE WHEN (lang = 'en' AND doc_id % 2 = 0) OR (lang <> 'en' AND doc_id % 4 = 0) THEN 'A' ELSE 'B' END AS corpus FROM d)"""


def chunk_sql(table: str) -> str:
    return f"ch AS (SELECT c AS chunk, count(*) AS n FROM (SELECT unnest(regexp_extract_all(text, '{PATTERN}')) AS c FROM {table}) GROUP BY c)"


SYMBOLS = """s0 AS (SELECT array_to_string(list_transform(range(0, CAST(octet_length(encode(chunk)) AS BIGINT)),
    lambda i: chr(CAST('0x' || substr(hex(encode(chunk)), CAST(2 * i + 1 AS INT), 2) AS INT))), '') AS sym, n FROM ch)"""


def train_sql(merges: int) -> str:
    return f"""WITH RECURSIVE {chunk_sql('benchmark')}, {SYMBOLS},
    r AS (SELECT 0 AS step, sym, n FROM s0 UNION ALL
          SELECT step + 1, replace(sym, top.pair, chr(256 + step)), n FROM r,
            (SELECT pair FROM (SELECT substr(sym, i, 2) AS pair, n FROM r, LATERAL (SELECT unnest(range(1, length(sym))) AS i)) GROUP BY pair ORDER BY sum(n) DESC, pair LIMIT 1) AS top
          WHERE step < {merges}),
    pc AS (SELECT step, substr(sym, i, 2) AS pair, sum(n) AS f FROM r, LATERAL (SELECT unnest(range(1, length(sym))) AS i) GROUP BY ALL),
    top AS (SELECT step, pair, f FROM (SELECT *, row_number() OVER (PARTITION BY step ORDER BY f DESC, pair) AS k FROM pc) WHERE k = 1 AND step < {merges}),
    len AS (SELECT step, sum(n * length(sym)) AS total FROM r GROUP BY step),
    log AS (SELECT CAST(top.step AS INT) AS "rank", CAST(unicode(substr(pair, 1, 1)) AS INT) AS "left", CAST(unicode(substr(pair, 2, 1)) AS INT) AS "right", CAST(256 + top.step AS INT) AS token,
        CAST(f AS BIGINT) AS freq, CAST(a.total - b.total AS BIGINT) AS repl FROM top JOIN len a ON a.step = top.step JOIN len b ON b.step = top.step + 1),
    ex AS (SELECT step, CAST(unicode(substr(sym, i, 1)) AS INT) AS token, CAST(sum(n) AS BIGINT) AS exposure FROM r, LATERAL (SELECT unnest(range(1, length(sym) + 1)) AS i) GROUP BY ALL)"""


def small(spark, sf, merges=SMALL):
    chunks = chunk_table(t(spark, sf, "benchmark"))
    return chunks, train_bpe(chunks, merges, "compact")


# corpus


@query(f"WITH {CORPORA} SELECT corpus, lang, CAST(sum(octet_length(encode(text))) AS BIGINT) AS bytes, count(*) AS docs FROM corpora GROUP BY ROLLUP (corpus, lang)")
def corpus_profile(spark, sf):
    return corpus.corpus_profile(corpus.build_corpora(t(spark, sf, "documents")))


@query(f"WITH {CORPORA} SELECT count(*) AS shared FROM corpora a JOIN corpora b ON a.text = b.text WHERE a.corpus = 'A' AND b.corpus = 'B'")
def corpus_disjoint(spark, sf):
    c = corpus.build_corpora(t(spark, sf, "documents"))
    return corpus.assert_disjoint(c.filter("corpus = 'A'"), c.filter("corpus = 'B'")).agg(F.count("*").alias("shared"))


@query("SELECT doc_id, lang, so_far FROM (SELECT doc_id, lang, CAST(sum(octet_length(encode(text))) OVER (PARTITION BY lang ORDER BY md5(doc_id || '0'), doc_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS so_far FROM documents) WHERE so_far <= 100000")
def corpus_cap(spark, sf):
    return corpus.cap_by_category(t(spark, sf, "documents"), "lang", 100_000).select("doc_id", "lang", "so_far")


@query("SELECT doc_id FROM documents WHERE CAST('0x' || substr(md5(doc_id || '0'), 1, 8) AS BIGINT) < CAST(0.25 * 4294967296 AS BIGINT)")
def corpus_sample(spark, sf):
    return corpus.shuffled_sample(t(spark, sf, "documents"), 0.25).select("doc_id")


@query("SELECT doc_id, array_to_string(list_filter(string_split(text, chr(10)), lambda x, i: i = 1 OR x <> string_split(text, chr(10))[i - 1]), chr(10)) AS text FROM documents")
def clean_repeated_lines(spark, sf):
    return t(spark, sf, "documents").select("doc_id", cleaning.drop_repeated_lines(F.col("text")).alias("text"))


@query(r"SELECT doc_id, regexp_replace(text, '[\x00-\x08\x0b\x0c\x0e-\x1f\x7f\x{FFFD}]', '', 'g') AS text FROM documents")
def clean_artifacts(spark, sf):
    return t(spark, sf, "documents").select("doc_id", cleaning.strip_artifacts(F.col("text")).alias("text"))


@query("""WITH l AS (SELECT doc_id, source, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM documents),
    c AS (SELECT source, line FROM l WHERE line <> '' GROUP BY ALL HAVING count(DISTINCT doc_id) >= 5),
    k AS (SELECT doc_id, string_agg(line, chr(10) ORDER BY pos) AS text FROM l ANTI JOIN c USING (source, line) GROUP BY doc_id)
    SELECT documents.doc_id, coalesce(k.text, '') AS text FROM documents LEFT JOIN k USING (doc_id)""")
def clean_boilerplate(spark, sf):
    return corpus.drop_boilerplate(t(spark, sf, "documents"))


@query(r"""SELECT page_id, regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<!--.*?-->', '', 'g'), '(?is)<script[^>]*>.*?</script>', '', 'g'),
    '(?is)<style[^>]*>.*?</style>', '', 'g'), '(?is)<nav[^>]*>.*?</nav>', '', 'g'), '(?s)<[^>]*>', '', 'g') AS body FROM pages""")
def clean_markup(spark, sf):
    return t(spark, sf, "pages").select("page_id", cleaning.strip_markup(F.col("html")).alias("body"))


# pretokenizer


@query(f"SELECT doc_id, CAST(len(regexp_extract_all(text, '{PATTERN}')) AS INT) AS chunks, md5(array_to_string(regexp_extract_all(text, '{PATTERN}'), chr(1))) AS cut FROM documents")
def pretok_chunks(spark, sf):
    c = pretokenize(F.col("text"))
    return t(spark, sf, "documents").select("doc_id", F.size(c).alias("chunks"), F.md5(F.array_join(c, "\x01").cast("binary")).alias("cut"))


@query(f"SELECT CAST(count(*) FILTER (WHERE array_to_string(regexp_extract_all(x, '{PATTERN}'), '') <> x) AS INT) AS lost FROM (SELECT text AS x FROM documents UNION ALL SELECT html FROM pages UNION ALL SELECT text FROM conversations)")
def pretok_roundtrip(spark, sf):
    d = t(spark, sf, "documents").select("text").unionByName(t(spark, sf, "pages").select(F.col("html").alias("text"))).unionByName(t(spark, sf, "conversations").select("text"))
    return d.agg(F.count_if(F.array_join(pretokenize(F.col("text")), "") != F.col("text")).cast("int").alias("lost"))


_KIND = "CASE " + " ".join(f"WHEN regexp_matches(c, '{p.replace('IsLatin', 'Latin')}') THEN '{k}'" for k, p in KINDS) + " ELSE 'other' END"


@query(f"SELECT lang, {_KIND} AS kind, CAST(sum(n) AS BIGINT) AS n FROM (SELECT lang, c, count(*) AS n FROM (SELECT lang, unnest(regexp_extract_all(text, '{PATTERN}')) AS c FROM documents) GROUP BY ALL) GROUP BY ALL")
def pretok_class_counts(spark, sf):
    """Chunks of each kind by language; a kind is found once for each distinct chunk."""
    chunks = texts(spark, sf, "documents").select("lang", F.explode(pretokenize(F.col("text"))).alias("c")).groupBy("lang", "c").agg(F.count("*").alias("n"))
    return chunks.groupBy("lang", chunk_kind(F.col("c")).alias("kind")).agg(F.sum("n").alias("n"))


# training


@query(f"WITH {CORPORA}, {chunk_sql('documents')}, {SYMBOLS} SELECT md5(sym) AS sym, n FROM s0")
def bpe_chunk_table(spark, sf):
    return chunk_table(texts(spark, sf, "documents")).select(F.md5(F.col("sym").cast("binary")).alias("sym"), "n")


@query(f"WITH {chunk_sql('documents')}, {SYMBOLS} SELECT hex(encode(substr(sym, i, 2))) AS pair, CAST(sum(n) AS BIGINT) AS f FROM s0, LATERAL (SELECT unnest(range(1, length(sym))) AS i) GROUP BY ALL")
def bpe_pair_counts(spark, sf):
    return pair_counts(chunk_table(texts(spark, sf, "documents"))).select(F.hex(F.encode("pair", "UTF-8")).alias("pair"), "f")


@query(f"""WITH {chunk_sql('documents')}, {SYMBOLS}, p AS (SELECT substr(sym, i, 2) AS pair, sum(n) AS f FROM s0, LATERAL (SELECT unnest(range(1, length(sym))) AS i) GROUP BY ALL ORDER BY f DESC, pair LIMIT 1)
    SELECT CAST(sum(n * (length(sym) - length(replace(sym, pair, chr(256))))) AS BIGINT) AS replaced FROM s0, p""")
def bpe_apply_merge(spark, sf):
    chunks = chunk_table(texts(spark, sf, "documents"))
    top = top_pairs(pair_counts(chunks)).first()
    size = lambda c: c.agg(F.sum(F.col("n") * F.char_length("sym")).alias("s"))
    return size(chunks).crossJoin(size(apply_merge(chunks, top.pair, 256)).withColumnRenamed("s", "after")).select((F.col("s") - F.col("after")).alias("replaced"))


@query(train_sql(SMALL) + ' SELECT "rank", "left", "right", token, freq, repl FROM log')
def bpe_first_merges(spark, sf):
    return small(spark, sf)[1].frame(spark).select("rank", "left", "right", "token", "freq", "repl")


@query(train_sql(8) + ' SELECT "rank", "left", "right", token, freq, repl FROM log')
def bpe_train_stepwise(spark, sf):
    return train_bpe(chunk_table(t(spark, sf, "benchmark")), 8, "stepwise").frame(spark).select("rank", "left", "right", "token", "freq", "repl")


@query(train_sql(SMALL) + ' SELECT "rank", "left", "right", token, freq, repl FROM log')
def bpe_train_batch(spark, sf):
    return train_bpe(chunk_table(t(spark, sf, "benchmark")), SMALL, "batch").frame(spark).select("rank", "left", "right", "token", "freq", "repl")


@query(train_sql(SMALL) + ' SELECT "rank", "left", "right", token, freq, repl FROM log')
def bpe_train_delta(spark, sf):
    return train_bpe(chunk_table(t(spark, sf, "benchmark")), SMALL, "delta").frame(spark).select("rank", "left", "right", "token", "freq", "repl")


@query(train_sql(SMALL) + ' SELECT "rank", "left", "right", token, freq, repl FROM log')
def bpe_resume_equal(spark, sf):
    """Nine merges by one strategy, resumed by another to the end: the log is the uninterrupted one."""
    chunks, log = small(spark, sf)
    part = train_bpe(chunks, 15, "delta", log.prefix(9))
    return train_bpe(chunks, SMALL, "batch", part).frame(spark).select("rank", "left", "right", "token", "freq", "repl")


@query("SELECT s AS strategy, TRUE AS equal FROM (SELECT unnest(['batch', 'compact', 'delta', 'stepwise']) AS s)")
def bpe_strategies_agree(spark, sf):
    chunks, log = small(spark, sf)
    full = train_bpe(chunks, 100, "compact")
    part = full.prefix(92)  # a job for each merge: the last eight alone
    chunks = over_all_cores(chunks).persist()
    logs = {s: train_bpe(chunks, 100, s, part if s == "stepwise" else None) for s in sorted(STRATEGIES)}
    return spark.createDataFrame([(s, x == full and full.prefix(SMALL) == log) for s, x in logs.items()], "strategy string, equal boolean")


@query(train_sql(100) + ' SELECT "rank", "left", "right", token, freq, repl FROM log')
def bpe_train_benchmark(spark, sf):
    return train_bpe(chunk_table(t(spark, sf, "benchmark")), 100, "batch").frame(spark).select("rank", "left", "right", "token", "freq", "repl")


# exposure and visibility


@query(train_sql(SMALL) + f" SELECT CAST(x.i AS INT) AS token, coalesce(exposure, 0) AS exposure FROM (SELECT unnest(range(0, {256 + SMALL})) AS i) x LEFT JOIN ex ON ex.token = x.i AND step = {SMALL}")
def exposure_count(spark, sf):
    return exposure_by_count(*small(spark, sf))


_Q["exposure_closed_form"] = lambda spark, sf: exposure_from_log(small(spark, sf)[1], spark)
_O["exposure_closed_form"] = _O["exposure_count"]


@query(train_sql(SMALL) + f" SELECT log.token, freq, coalesce(exposure, 0) AS exposure, round((freq - coalesce(exposure, 0)) / CAST(freq AS DOUBLE), 4) AS absorbed FROM log LEFT JOIN ex ON ex.token = log.token AND step = {SMALL}")
def absorbed_share(spark, sf):
    return absorption(small(spark, sf)[1], spark)


@query(train_sql(SLOTS) + f" SELECT ratio, CAST(ceil(CAST(ratio AS DECIMAL(3,2)) * freq) AS BIGINT) AS tau FROM log, (VALUES ('0.2'), ('0.3'), ('0.4')) r(ratio) WHERE \"rank\" = {SLOTS - 1}")
def tau_ratio(spark, sf):
    log = small(spark, sf, SLOTS)[1]
    return spark.createDataFrame([(r, tau_from_ratio(log, SLOTS, r)) for r in workloads.RATIOS], "ratio string, tau long")


#: With one merge per resumed step the trained prefix is the least m whose own exposures leave enough eligible.
VISIBLE_SQL = train_sql(SMALL * 4) + f""", tau AS (SELECT ceil(CAST('0.8' AS DECIMAL(3,2)) * freq) AS tau FROM log WHERE "rank" = {SLOTS - 1}),
    em AS (SELECT m.m, log.token, coalesce(ex.exposure, 0) >= tau AS eligible, coalesce(ex.exposure, 0) AS exposure FROM (SELECT unnest(range({SLOTS}, 97)) AS m) m JOIN log ON log."rank" < m.m CROSS JOIN tau LEFT JOIN ex ON ex.step = m.m AND ex.token = log.token),
    best AS (SELECT min(m) AS m FROM (SELECT m FROM em WHERE eligible GROUP BY m HAVING count(*) >= {SLOTS})),
    scan AS (SELECT token, eligible, exposure, sum(CASE WHEN eligible THEN 1 ELSE 0 END) OVER (ORDER BY token ROWS UNBOUNDED PRECEDING) AS run FROM em JOIN best USING (m)),
    cut AS (SELECT token, eligible, exposure FROM scan WHERE run < {SLOTS} OR (run = {SLOTS} AND eligible))"""


@query(VISIBLE_SQL + " SELECT token, eligible AS visible, exposure FROM cut")
def visible_select(spark, sf):
    chunks, log = small(spark, sf)
    tok, _ = reallocate(chunks, log, VISIBLE, "0.8")
    return tok.frame(spark).filter("kind in ('learned', 'internal')").select("token", "visible", "exposure")


@query(VISIBLE_SQL + f""" SELECT token, CAST(CASE WHEN eligible THEN 255 + row_number() OVER (PARTITION BY eligible ORDER BY token) ELSE {VISIBLE - 1} + row_number() OVER (PARTITION BY eligible ORDER BY token) END AS INT) AS export_id FROM cut""")
def visible_export_ids(spark, sf):
    chunks, log = small(spark, sf)
    tok, _ = reallocate(chunks, log, VISIBLE, "0.8")
    return tok.frame(spark).filter("kind in ('learned', 'internal')").select("token", "export_id")


@query(train_sql(SLOTS) + f", tau AS (SELECT ceil(CAST('0.8' AS DECIMAL(3,2)) * freq) AS tau FROM log WHERE \"rank\" = {SLOTS - 1}) SELECT log.token, coalesce(exposure, 0) >= tau AS visible FROM log CROSS JOIN tau LEFT JOIN ex ON ex.token = log.token AND step = {SLOTS}")
def pruned(spark, sf):
    log = small(spark, sf, SLOTS)[1]
    return prune_only(log, tau_from_ratio(log, SLOTS, "0.8"), VISIBLE).frame(spark).filter("kind in ('learned', 'internal')").select("token", "visible")


@query("SELECT TRUE AS refused")
def infeasible_threshold(spark, sf):
    chunks, log = small(spark, sf)
    try:
        reallocate(chunks, log, VISIBLE, tau=10**9)
        refused = False
    except InsufficientCandidates:
        refused = True
    return spark.createDataFrame([(refused,)], "refused boolean")


# encoding and lengths


def vp(spark, sf):
    chunks, log = small(spark, sf)
    tok, log = reallocate(chunks, log, VISIBLE, "0.8")
    return chunks, tok, log


@query(train_sql(SLOTS) + f" SELECT CAST(sum(n * length(sym)) AS BIGINT) AS tokens FROM r WHERE step = {SLOTS}")
def encode_length(spark, sf):
    chunks, log = small(spark, sf, SLOTS)
    return spark.createDataFrame([(encoded_length(chunks, export_standard(log, VISIBLE)),)], "tokens long")


_Q["length_closed_form"] = lambda spark, sf: spark.createDataFrame([(length_from_log(small(spark, sf, SLOTS)[1]),)], "tokens long")
_O["length_closed_form"] = _O["encode_length"]


@query("SELECT TRUE AS equal")
def encode_vp_agrees(spark, sf):
    """Encoding the texts, their distinct chunks in columns, and the closed form give one length."""
    chunks, tok, log = vp(spark, sf)
    texts = encode(t(spark, sf, "benchmark"), tok, id_col="item_id").agg(F.sum(F.size("ids"))).first()[0]
    native = encode_chunks_native(chunks, tok).agg(F.sum(F.col("n") * F.col("tokens"))).first()[0]
    return spark.createDataFrame([(texts == native == encoded_length(chunks, tok) == vp_length_from_log(tok, log),)], "equal boolean")


#: After each merge: the bytes that every token spells, how many visible tokens it becomes, and their ids.
STATE_SQL = VISIBLE_SQL + """, named AS (SELECT token, eligible, CASE WHEN eligible THEN 255 + row_number() OVER (PARTITION BY eligible ORDER BY token) END AS export_id FROM cut),
    state AS (SELECT 0 AS step, list_transform(range(256), lambda i: chr(CAST(i AS INT))) AS l, list_transform(range(256), lambda i: [i]) AS e UNION ALL
        SELECT step + 1, list_append(l, l["left" + 1] || l["right" + 1]), list_append(e, CASE WHEN coalesce(eligible, TRUE) THEN [CAST(export_id AS BIGINT)] ELSE list_concat(e["left" + 1], e["right" + 1]) END)
        FROM state JOIN log ON "rank" = step LEFT JOIN named ON named.token = log.token WHERE step < 96),
    last AS (SELECT l, e, step AS k FROM state WHERE step = (SELECT count(*) FROM cut))"""

ITEMS_SQL = f"""occ AS (SELECT item_id, unnest(c) AS chunk, unnest(range(1, len(c) + 1)) AS pos FROM (SELECT item_id, regexp_extract_all(text, '{PATTERN}') AS c FROM benchmark)),
    {SYMBOLS.replace('s0 AS', 'sc AS').replace('AS sym, n FROM ch', 'AS sym, chunk FROM ch')},
    enc AS (SELECT 0 AS step, chunk, sym FROM sc UNION ALL SELECT step + 1, chunk, replace(sym, chr("left") || chr("right"), chr(token)) FROM enc JOIN log ON "rank" = step WHERE step < 96)"""


def _ids(spark, sf, tok):
    return encode(t(spark, sf, "benchmark"), tok, id_col="item_id").select("item_id", F.array_join(F.transform("ids", lambda i: i.cast("string")), " ").alias("ids"))


@query(train_sql(96) + f""", {ITEMS_SQL} SELECT item_id, string_agg(array_to_string(list_transform(string_split(sym, ''), lambda c: unicode(c)), ' '), ' ' ORDER BY pos) AS ids FROM occ JOIN enc USING (chunk) WHERE step = {SLOTS} GROUP BY item_id""")
def encode_std(spark, sf):
    return _ids(spark, sf, export_standard(small(spark, sf, SLOTS)[1], VISIBLE))


@query(STATE_SQL + f""", {ITEMS_SQL} SELECT item_id, string_agg(array_to_string(flatten(list_transform(string_split(sym, ''), lambda c: e[unicode(c) + 1])), ' '), ' ' ORDER BY pos) AS ids FROM occ JOIN enc USING (chunk) JOIN last ON step = k GROUP BY item_id""")
def encode_vp(spark, sf):
    return _ids(spark, sf, vp(spark, sf)[1])


@query(STATE_SQL + """ SELECT CAST(i AS INT) AS token, array_to_string(e[i + 1], ' ') AS becomes FROM last, LATERAL (SELECT unnest(range(0, 256 + k)) AS i)""")
def expand_map(spark, sf):
    tok = vp(spark, sf)[1]
    ids = tok.export_ids()
    return spark.createDataFrame([(i, " ".join(str(ids[x]) for x in e)) for i, e in enumerate(tok.expansions())], "token int, becomes string")


@query("SELECT item_id, text FROM benchmark")
def decode_roundtrip(spark, sf):
    _, tok, _ = vp(spark, sf)
    return decode_ids(encode(t(spark, sf, "benchmark"), tok, id_col="item_id"), tok, "item_id")


@query()
def encode_documents(spark, sf):
    """All documents under the largest tokenizer trained on them, with an end token."""
    s = workloads.study(spark, sf)
    tok = s.tokenizer("AB", s.budgets[-1], "0.4")
    return encode(texts(spark, sf, "documents"), tok).select("doc_id", F.size(with_specials(F.col("ids"), tok)).alias("tokens"))


@query("SELECT TRUE AS equal")
def min_tokens_agree(spark, sf):
    """The program over positions and the fold over joined edges, on all chunks."""
    chunks, tok, _ = vp(spark, sf)
    a, b = min_tokens(chunks, vocabulary(tok)), min_tokens_relational(chunks, vocabulary(tok))
    return spark.createDataFrame([(a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty(),)], "equal boolean")


@query(STATE_SQL + f""", words AS (SELECT 'standard' AS method, l[257:{256 + SLOTS}] AS w FROM last UNION ALL SELECT 'reallocated', (SELECT list(l[token + 1]) FROM cut, last WHERE eligible)),
    dp AS (SELECT method, sym, n, length(sym) AS i, [CAST(0 AS BIGINT)] AS costs, w FROM s0, words UNION ALL
        SELECT method, sym, n, i - 1, list_prepend(1 + list_min(list_prepend(costs[1], list_transform(list_filter(w, lambda x: starts_with(substr(sym, i), x)), lambda x: costs[length(x)]))), costs), w FROM dp WHERE i > 0),
    low AS (SELECT method, CAST(sum(n * costs[1]) AS BIGINT) AS minimum FROM dp WHERE i = 0 GROUP BY method),
    native AS (SELECT 'standard' AS method, CAST(sum(n * length(sym)) AS BIGINT) AS native FROM r WHERE step = {SLOTS} UNION ALL
        SELECT 'reallocated', CAST(sum(exposure * len(e[token + 1])) AS BIGINT) FROM ex JOIN last ON step = k)
    SELECT method, native, minimum FROM native JOIN low USING (method)""")
def min_versus_native(spark, sf):
    chunks, tok, log = vp(spark, sf)
    std = export_standard(log, VISIBLE)
    rows = [(name, encoded_length(chunks, x), min_length(chunks, vocabulary(x))) for name, x in (("standard", std), ("reallocated", tok))]
    return spark.createDataFrame(rows, "method string, native long, minimum long")


@query(STATE_SQL + f""", spent AS (SELECT CAST(coalesce(sum(exposure * (len(e[token + 1]) - 1)), 0) AS BIGINT) AS cost FROM ex JOIN last ON step = k),
    size AS (SELECT a.total AS standard, CAST(a.total - b.total AS BIGINT) AS gain, k FROM last JOIN len b ON b.step = k JOIN len a ON a.step = {SLOTS})
    SELECT CAST(k AS BIGINT) AS merges, CAST(k - {SLOTS} AS BIGINT) AS internal, round(100.0 * (k - {SLOTS}) / {SLOTS}, 2) AS share, gain AS candidate_gain, cost AS expansion_cost, gain - cost AS net, round(100.0 * CAST(gain - cost AS DOUBLE) / CAST(standard AS DOUBLE), 2) AS delta FROM size, spent""")
def decompose_delta(spark, sf):
    """The trade-off of the small reallocation: what later candidates gain, what expanding internal tokens costs."""
    _, tok, log = vp(spark, sf)
    std = export_standard(log, VISIBLE)
    gain, cost, net = ms.decompose(tok, std, log)
    row = (len(tok.log), len(tok.internal), len(tok.internal), SLOTS, gain, cost, net, length_from_log(std.log))
    df = spark.createDataFrame([row], "merges long, internal long, i long, slots long, candidate_gain long, expansion_cost long, net long, standard long")
    return df.select("merges", "internal", ms.percent(F.col("i"), F.col("slots")).alias("share"), "candidate_gain", "expansion_cost", "net", ms.percent(F.col("net"), F.col("standard")).alias("delta"))


@query(STATE_SQL + """, edge AS (SELECT "left" AS child, token AS parent FROM log, last WHERE "rank" < k UNION SELECT "right", token FROM log, last WHERE "rank" < k),
    up AS (SELECT child, parent FROM edge UNION SELECT up.child, edge.parent FROM up JOIN edge ON edge.child = up.parent),
    seen AS (SELECT token FROM cut WHERE eligible)
    SELECT token, (SELECT count(*) FROM edge WHERE child = token AND parent IN (FROM seen)) AS visible_parents, (SELECT count(*) FROM up WHERE child = token AND parent IN (FROM seen)) AS visible_ancestors FROM cut WHERE NOT eligible""")
def internal_support(spark, sf):
    """How many visible tokens are made of each internal one, at once and in the end."""
    return spark.createDataFrame(ms.support(vp(spark, sf)[1]), "token int, visible_parents long, visible_ancestors long")


@query("SELECT TRUE AS supported")
def support_orphans(spark, sf):
    """Of the largest budget: every internal token has a visible ancestor."""
    s = workloads.study(spark, sf)
    tok = s.tokenizer("AB", s.budgets[-1], "0.4")
    return spark.createDataFrame([(all(above for _, _, above in ms.support(tok)),)], "supported boolean")


@query(train_sql(SMALL * 4) + f""", tau AS (SELECT ceil(CAST('0.6' AS DECIMAL(3,2)) * freq) AS tau FROM log WHERE "rank" = {SLOTS - 1}),
    all_ AS (SELECT log.token, coalesce(exposure, 0) >= tau AS eligible FROM log CROSS JOIN tau LEFT JOIN ex ON ex.token = log.token AND ex.step = {SMALL * 4}),
    scan AS (SELECT *, sum(CASE WHEN eligible THEN 1 ELSE 0 END) OVER (ORDER BY token ROWS UNBOUNDED PRECEDING) AS run FROM all_)
    SELECT token, eligible AS visible FROM scan WHERE run < {SLOTS} OR (run = {SLOTS} AND eligible)""")
def reexport_threshold(spark, sf):
    """One trained tree under another threshold, without training: exposures of the whole tree decide."""
    log = small(spark, sf, SMALL * 4)[1]
    tok = reexport(log, exposures(log), tau_from_ratio(log, SLOTS, "0.6"), VISIBLE)
    return tok.frame(spark).filter("kind in ('learned', 'internal')").select("token", "visible")


@query("SELECT TRUE AS equal")
def exposure_agrees_on_documents(spark, sf):
    """Counting the symbols of all documents after every merge of the largest vocabulary, and the closed form from the log."""
    s = workloads.study(spark, sf)
    log = s.tokenizer("AB", s.budgets[-1], "0.4").log
    counted, closed = exposure_by_count(s.chunks("AB"), log), exposure_from_log(log, spark)
    return spark.createDataFrame([(counted.exceptAll(closed).isEmpty() and closed.exceptAll(counted).isEmpty(),)], "equal boolean")


@query()
def slot_moves(spark, sf):
    s = workloads.study(spark, sf)
    return ms.slot_moves(s.tokenizer("AB", s.budgets[-1]), s.tokenizer("AB", s.budgets[-1], "0.4"), spark)


@query(STATE_SQL + f""" SELECT token, move, array_to_string(list_transform(string_split(l[token + 1], ''), lambda c: printf('%02x', unicode(c))), '') AS bytes
    FROM (SELECT token, CASE WHEN token < {256 + SLOTS} AND NOT eligible THEN 'lost' WHEN token >= {256 + SLOTS} AND eligible THEN 'gained' END AS move FROM cut), last WHERE move IS NOT NULL""")
def small_slot_moves(spark, sf):
    _, tok, log = vp(spark, sf)
    return ms.slot_moves(export_standard(log, VISIBLE), tok, spark)


@query(train_sql(SLOTS) + f""", sizes AS (SELECT CAST(step AS INT) AS merges, CAST(total AS BIGINT) AS tokens, lead(total) OVER (ORDER BY step) AS after, (SELECT total FROM len WHERE step = 0) AS bytes FROM len WHERE step IN (16, 32, 48, {SLOTS}))
    SELECT merges, tokens, round(CAST(bytes AS DOUBLE) / tokens, 4) AS bytes_per_token, round(100.0 * CAST(tokens - after AS DOUBLE) / tokens, 2) AS reduction FROM sizes""")
def small_marginal_curve(spark, sf):
    """What the next larger standard vocabulary saves, and bytes per token: lengths of every size from one log."""
    log = small(spark, sf, SLOTS)[1]
    rows = [("X", "X", m, "0", "native", length_from_log(log, m), 0) for m in (16, 32, 48, SLOTS)]
    df = spark.createDataFrame(rows, ms.LENGTHS)
    saved = ms.marginal_reduction(df).select("n_visible", "reduction")
    return df.join(saved, "n_visible", "left").select(F.col("n_visible").alias("merges"), "tokens", ms.bytes_per_token(F.lit(sum(log.byte_counts)), F.col("tokens")).alias("bytes_per_token"), "reduction")


THRESHOLDS = ["0.6", "0.7", "0.8"]
THRESHOLD_SQL = train_sql(SMALL * 4) + f""", tau AS (SELECT ratio, ceil(CAST(ratio AS DECIMAL(3,2)) * freq) AS tau FROM log, (SELECT unnest({THRESHOLDS}) AS ratio) WHERE "rank" = {SLOTS - 1}),
    em AS (SELECT ratio, m.m, log.token, coalesce(ex.exposure, 0) >= tau AS eligible FROM (SELECT unnest(range({SLOTS}, 97)) AS m) m JOIN log ON log."rank" < m.m CROSS JOIN tau LEFT JOIN ex ON ex.step = m.m AND ex.token = log.token),
    best AS (SELECT ratio, min(m) AS m FROM (SELECT ratio, m FROM em WHERE eligible GROUP BY ratio, m HAVING count(*) >= {SLOTS}) GROUP BY ratio),
    cut AS (SELECT ratio, token, eligible FROM em JOIN best USING (ratio, m)),
    fan AS (SELECT ratio, 0 AS step, list_transform(range(256), lambda i: CAST(1 AS BIGINT)) AS f FROM tau UNION ALL
        SELECT fan.ratio, step + 1, list_append(f, CASE WHEN coalesce(eligible, TRUE) THEN 1 ELSE f["left" + 1] + f["right" + 1] END)
        FROM fan JOIN log ON "rank" = step LEFT JOIN cut ON cut.ratio = fan.ratio AND cut.token = log.token WHERE step < 96)"""


@query(THRESHOLD_SQL + f""", size AS (SELECT best.ratio, m, CAST(sum(exposure * f[token + 1]) AS BIGINT) AS tokens FROM best JOIN fan ON fan.ratio = best.ratio AND step = m JOIN ex ON ex.step = m GROUP BY ALL)
    SELECT ratio, CAST(tau AS BIGINT) AS tau, CAST(m - {SLOTS} AS INT) AS internal, round(100.0 * (m - {SLOTS}) / {SLOTS}, 2) AS share, tokens, round(100.0 * CAST(total - tokens AS DOUBLE) / total, 4) AS delta
    FROM size JOIN tau USING (ratio) JOIN len ON len.step = {SLOTS}""")
def small_thresholds(spark, sf):
    """Internal tokens, their share, the length and what it saves, at three thresholds on one corpus."""
    chunks, log = small(spark, sf)
    rows, taus = [], []
    for r in THRESHOLDS:
        tok, log = reallocate(chunks, log, VISIBLE, r)
        rows.append(("X", "X", VISIBLE, r, "native", vp_length_from_log(tok, log), len(tok.internal)))
        taus.append((r, tok.tau))
    rows.append(("X", "X", VISIBLE, "0", "native", length_from_log(log, SLOTS), 0))
    df = spark.createDataFrame(rows, ms.LENGTHS)
    out = ms.reduction(df).select("ratio", F.col("len_vp").alias("tokens"), "delta").join(ms.internal_share(df).select("ratio", "internal", "share"), "ratio")
    return out.join(spark.createDataFrame(taus, "ratio string, tau long"), "ratio")


@query(THRESHOLD_SQL + """ SELECT a.ratio AS low, b.ratio AS high, count(*) FILTER (WHERE a.token NOT IN (SELECT token FROM cut c WHERE c.ratio = b.ratio AND NOT c.eligible)) AS violations
    FROM cut a JOIN best b ON b.ratio > a.ratio WHERE NOT a.eligible GROUP BY ALL""")
def small_nesting(spark, sf):
    """Tokens internal at a lower threshold and not at a higher one."""
    chunks, log = small(spark, sf)
    toks = []
    for r in THRESHOLDS:
        tok, log = reallocate(chunks, log, VISIBLE, r)
        toks.append((r, tok))
    rows = [(a, b, len(ms.nesting_violations(x, y))) for i, (a, x) in enumerate(toks) for b, y in toks[i + 1 :] if x.internal]
    return spark.createDataFrame(rows, "low string, high string, violations long")


_Q.update(workloads.WORKLOADS)


# the experiments over three trainings, on the passages of benchmark: even, odd and all items in place of the corpora

SLOT_SIZES, TRIO_RATIOS = [40, 64, 72], ["0.4", "0.5", "0.7"]


def small_study(spark, sf):
    items = t(spark, sf, "benchmark")
    part = {"A": items.filter("item_id % 2 = 0"), "B": items.filter("item_id % 2 = 1"), "AB": items}
    return workloads.Study(spark, lambda name: chunk_table(part[name]), [260 + n for n in SLOT_SIZES], TRIO_RATIOS)


MOST_MERGES = 88
TRIO = "tr AS (SELECT unnest(['A', 'B', 'AB']) AS tr), items AS (SELECT tr, text FROM benchmark, tr WHERE tr = 'AB' OR (tr = 'A') = (item_id % 2 = 0))"
#: Three trainings at once; a step's pair is the most frequent one of its training.
TRIO_SQL = f"""WITH RECURSIVE {TRIO},
    ch AS (SELECT tr, c AS chunk, count(*) AS n FROM (SELECT tr, unnest(regexp_extract_all(text, '{PATTERN}')) AS c FROM items) GROUP BY ALL),
    {SYMBOLS.replace("AS sym, n FROM ch", "AS sym, tr, n FROM ch")},
    r AS (SELECT 0 AS step, tr, sym, n FROM s0 UNION ALL
        SELECT step + 1, r.tr, replace(sym, top.pair, chr(256 + step)), n FROM r JOIN
            (SELECT tr, pair FROM (SELECT tr, pair, row_number() OVER (PARTITION BY tr ORDER BY f DESC, pair) AS k FROM
                (SELECT tr, substr(sym, i, 2) AS pair, sum(n) AS f FROM r, LATERAL (SELECT unnest(range(1, length(sym))) AS i) GROUP BY ALL)) WHERE k = 1) AS top USING (tr)
        WHERE step < {MOST_MERGES}),
    pc AS (SELECT step, tr, substr(sym, i, 2) AS pair, sum(n) AS f FROM r, LATERAL (SELECT unnest(range(1, length(sym))) AS i) GROUP BY ALL),
    top AS (SELECT step, tr, pair, f FROM (SELECT *, row_number() OVER (PARTITION BY step, tr ORDER BY f DESC, pair) AS k FROM pc) WHERE k = 1 AND step < {MOST_MERGES}),
    log AS (SELECT tr, step AS "rank", unicode(substr(pair, 1, 1)) AS "left", unicode(substr(pair, 2, 1)) AS "right", 256 + step AS token, f AS freq FROM top),
    ex AS (SELECT step, tr, unicode(substr(sym, i, 1)) AS token, sum(n) AS exposure FROM r, LATERAL (SELECT unnest(range(1, length(sym) + 1)) AS i) GROUP BY ALL),
    size AS (SELECT unnest({SLOT_SIZES}) AS slots),
    tau AS (SELECT tr, slots, ratio, ceil(CAST(ratio AS DECIMAL(3,2)) * freq) AS tau FROM log, size, (SELECT unnest({TRIO_RATIOS}) AS ratio) WHERE "rank" = slots - 1 AND slots < {SLOT_SIZES[-1]}),
    em AS (SELECT tau.*, m.m, log.token, coalesce(ex.exposure, 0) >= tau AS eligible FROM tau JOIN (SELECT unnest(range(0, {MOST_MERGES + 1})) AS m) m ON m.m >= slots
        JOIN log ON log.tr = tau.tr AND log."rank" < m.m LEFT JOIN ex ON ex.step = m.m AND ex.tr = tau.tr AND ex.token = log.token),
    best AS (SELECT tr, slots, ratio, min(m) AS m FROM (SELECT tr, slots, ratio, m FROM em WHERE eligible GROUP BY ALL HAVING count(*) >= any_value(slots)) GROUP BY ALL),
    cut AS (SELECT em.tr, em.slots, em.ratio, token, eligible FROM em JOIN best ON em.tr = best.tr AND em.slots = best.slots AND em.ratio = best.ratio AND em.m = best.m),
    fan AS (SELECT tr, slots, ratio, 0 AS step, list_transform(range(256), lambda i: CAST(1 AS BIGINT)) AS f FROM tau UNION ALL
        SELECT fan.tr, fan.slots, fan.ratio, step + 1, list_append(f, CASE WHEN coalesce(eligible, TRUE) THEN 1 ELSE f["left" + 1] + f["right" + 1] END)
        FROM fan JOIN log ON log.tr = fan.tr AND "rank" = step LEFT JOIN cut ON cut.tr = fan.tr AND cut.slots = fan.slots AND cut.ratio = fan.ratio AND cut.token = log.token WHERE step < {MOST_MERGES}),
    cells AS (SELECT a.tr, b.tr AS ev FROM tr a, tr b WHERE b.tr <> 'AB' OR a.tr = 'AB'),
    enc AS (SELECT 0 AS step, cells.tr, ev, sym, n FROM cells JOIN s0 ON s0.tr = ev UNION ALL
        SELECT step + 1, enc.tr, ev, replace(sym, chr(CAST("left" AS INT)) || chr(CAST("right" AS INT)), chr(CAST(token AS INT))), n FROM enc JOIN log ON log.tr = enc.tr AND "rank" = step WHERE step < {MOST_MERGES}),
    std AS (SELECT tr, ev, slots, sum(n * length(sym)) AS tokens FROM enc JOIN size ON step = slots GROUP BY ALL),
    seen AS (SELECT step, tr, ev, unicode(substr(sym, i, 1)) AS token, sum(n) AS exposure FROM enc, LATERAL (SELECT unnest(range(1, length(sym) + 1)) AS i) GROUP BY ALL),
    vp AS (SELECT best.tr, ev, best.slots, best.ratio, m - best.slots AS internal, sum(exposure * f[token + 1]) AS tokens FROM best JOIN fan ON fan.tr = best.tr AND fan.slots = best.slots AND fan.ratio = best.ratio AND fan.step = m
        JOIN seen ON seen.step = m AND seen.tr = best.tr GROUP BY ALL),
    cell AS (SELECT vp.*, std.tokens AS std, round(100.0 * CAST(std.tokens - vp.tokens AS DOUBLE) / CAST(std.tokens AS DOUBLE), 4) AS delta FROM vp JOIN std USING (tr, ev, slots))"""
NAMED = "tr AS train, ev AS eval, CAST(slots + 260 AS INT) AS n_visible"


@query(TRIO_SQL + f" SELECT {NAMED}, 'native' AS encoder, ratio, CAST(std AS BIGINT) AS len_std, CAST(tokens AS BIGINT) AS len_vp, delta FROM cell")
def small_w03_lengths(spark, sf):
    return workloads.w03_lengths(small_study(spark, sf))


@query(TRIO_SQL + " SELECT tr AS train, CAST(slots + 260 AS INT) AS n_visible, ratio, CAST(internal AS INT) AS internal, round(100.0 * internal / slots, 2) AS share FROM vp WHERE tr = ev")
def small_w04_internal_shares(spark, sf):
    return workloads.w04_internal_shares(small_study(spark, sf))


@query(TRIO_SQL + f""", lost AS (SELECT a.tr, a.slots, b.ratio, count(*) FILTER (WHERE h.eligible IS NULL OR h.eligible) AS violations FROM cut a JOIN tau b ON b.tr = a.tr AND b.slots = a.slots AND b.ratio = CASE a.ratio WHEN '{TRIO_RATIOS[0]}' THEN '{TRIO_RATIOS[1]}' WHEN '{TRIO_RATIOS[1]}' THEN '{TRIO_RATIOS[2]}' END
        LEFT JOIN cut h ON h.tr = a.tr AND h.slots = a.slots AND h.ratio = b.ratio AND h.token = a.token WHERE NOT a.eligible GROUP BY ALL)
    SELECT {NAMED}, ratio, CAST(internal AS INT) AS internal, delta, CAST(coalesce(violations, 0) AS INT) AS violations, tokens < lag(tokens) OVER w AS saves_more, internal >= lag(internal) OVER w AS hides_more,
        internal >= lag(internal) OVER (PARTITION BY tr, ev, ratio ORDER BY slots) AS grows FROM cell LEFT JOIN lost USING (tr, slots, ratio) WINDOW w AS (PARTITION BY tr, ev, slots ORDER BY ratio)""")
def small_w05_threshold_effect(spark, sf):
    return workloads.w05_threshold_effect(small_study(spark, sf))


@query(TRIO_SQL + f""", steps AS (SELECT tr, ev, slots, lead(slots) OVER w AS next, round(100.0 * CAST(tokens - lead(tokens) OVER w AS DOUBLE) / CAST(tokens AS DOUBLE), 2) AS reduction FROM std WHERE tr = ev WINDOW w AS (PARTITION BY tr ORDER BY slots))
    SELECT {NAMED}, CAST(next + 260 AS INT) AS next_n, reduction, delta, round(delta / reduction, 4) AS relative FROM steps JOIN cell USING (tr, ev, slots) WHERE ratio = '{TRIO_RATIOS[-1]}'""")
def small_w06_gain_beside_larger_vocabulary(spark, sf):
    return workloads.w06_gain_beside_larger_vocabulary(small_study(spark, sf))


#: Fewest tokens of every evaluation corpus under the standard and the strictest reallocated vocabularies trained on all items.
LEAST_SQL = TRIO_SQL + f""", spelled AS (SELECT 0 AS step, list_transform(range(256), lambda i: chr(CAST(i AS INT))) AS l UNION ALL
        SELECT step + 1, list_append(l, l["left" + 1] || l["right" + 1]) FROM spelled JOIN log ON "rank" = step AND tr = 'AB' WHERE step < {MOST_MERGES}),
    names AS (SELECT l FROM spelled WHERE step = {MOST_MERGES}),
    words AS (SELECT '0' AS ratio, slots, l[257:256 + slots] AS w FROM names, size WHERE slots < {SLOT_SIZES[-1]} UNION ALL
        SELECT ratio, slots, list(l[token + 1]) FROM cut, names WHERE eligible AND tr = 'AB' AND ratio = '{TRIO_RATIOS[-1]}' GROUP BY ALL),
    dp AS (SELECT ratio, slots, tr AS ev, sym, n, length(sym) AS i, [CAST(0 AS BIGINT)] AS costs, w FROM s0, words UNION ALL
        SELECT ratio, slots, ev, sym, n, i - 1, list_prepend(1 + list_min(list_prepend(costs[1], list_transform(list_filter(w, lambda x: starts_with(substr(sym, i), x)), lambda x: costs[length(x)]))), costs), w FROM dp WHERE i > 0),
    low AS (SELECT ratio, slots, ev, sum(n * costs[1]) AS minimum FROM dp WHERE i = 0 GROUP BY ALL),
    both_ways AS (SELECT low.*, coalesce(vp.tokens, std.tokens) AS native FROM low JOIN std ON std.tr = 'AB' AND std.ev = low.ev AND std.slots = low.slots LEFT JOIN vp ON vp.tr = 'AB' AND vp.ev = low.ev AND vp.slots = low.slots AND vp.ratio = low.ratio)"""


@query(LEAST_SQL + f""" SELECT 'AB' AS train, v.ev AS eval, CAST(v.slots + 260 AS INT) AS n_visible, 'minimum' AS encoder, v.ratio, CAST(s.minimum AS BIGINT) AS len_std, CAST(v.minimum AS BIGINT) AS len_vp,
    round(100.0 * CAST(s.minimum - v.minimum AS DOUBLE) / CAST(s.minimum AS DOUBLE), 4) AS delta FROM low v JOIN low s ON s.ev = v.ev AND s.slots = v.slots AND s.ratio = '0' WHERE v.ratio <> '0'""")
def small_w08_minimum_tokens(spark, sf):
    return workloads.w08_minimum_tokens(small_study(spark, sf))


@query(LEAST_SQL + """ SELECT ev AS eval, CAST(slots + 260 AS INT) AS n_visible, ratio, CAST(native AS BIGINT) AS native, CAST(minimum AS BIGINT) AS minimum, minimum < native AS below,
    round(100.0 * CAST(native - minimum AS DOUBLE) / CAST(native AS DOUBLE), 4) AS shorter FROM both_ways""")
def small_w09_minimum_below_native(spark, sf):
    return workloads.w09_minimum_below_native(small_study(spark, sf))


@query(TRIO_SQL + f""", prunes AS (SELECT tau.tr, tau.slots, log.token, coalesce(ex.exposure, 0) >= tau.tau AS eligible FROM tau JOIN log ON log.tr = tau.tr AND log."rank" < tau.slots
        LEFT JOIN ex ON ex.tr = tau.tr AND ex.token = log.token AND ex.step = tau.slots WHERE ratio = '{TRIO_RATIOS[-1]}'),
    pfan AS (SELECT tr, slots, 0 AS step, list_transform(range(256), lambda i: CAST(1 AS BIGINT)) AS f FROM tau WHERE ratio = '{TRIO_RATIOS[-1]}' UNION ALL
        SELECT pfan.tr, pfan.slots, step + 1, list_append(f, CASE WHEN eligible THEN 1 ELSE f["left" + 1] + f["right" + 1] END) FROM pfan JOIN log ON log.tr = pfan.tr AND "rank" = step JOIN prunes ON prunes.tr = pfan.tr AND prunes.slots = pfan.slots AND prunes.token = log.token WHERE step < pfan.slots),
    pruned AS (SELECT pfan.tr, pfan.slots, sum(exposure * f[token + 1]) AS tokens FROM pfan JOIN ex ON ex.tr = pfan.tr AND ex.step = pfan.slots WHERE pfan.step = pfan.slots GROUP BY ALL),
    kept AS (SELECT tr, slots, count(*) FILTER (WHERE eligible) AS left_ FROM prunes GROUP BY ALL)
    SELECT tr AS train, CAST(slots + 260 AS INT) AS n_visible, method, CAST(visible AS INT) AS visible, CAST(tokens AS BIGINT) AS tokens FROM (
        SELECT tr, slots, 'standard' AS method, slots + 260 AS visible, tokens FROM std WHERE tr = ev AND slots < {SLOT_SIZES[-1]} UNION ALL
        SELECT tr, slots, 'prune_only', left_ + 260, tokens FROM pruned JOIN kept USING (tr, slots) UNION ALL
        SELECT tr, slots, 'reallocated', slots + 260, tokens FROM vp WHERE tr = ev AND ratio = '{TRIO_RATIOS[-1]}')""")
def small_w12_prune_only(spark, sf):
    return workloads.w12_prune_only(small_study(spark, sf))


#: Inputs of the pretokenizer whose scripts, runs and technical forms the tables lack.
FIXTURES = [
    "a b", "a  b", "x\n\ty", "\r\nx\r", "user_id", "déjà vu", "don't", "C'était", "GPT-4", "GPT4", "IPv6", "COVID-19", "Node.js", "file.java", "app.jsonl", "x.pyramid", "x.py, y.html.", ".py", "C++ C# F#", "abC#", "3.14", "10-20", "1.2.3-4", "123abc",
    "abc123", "1949年6月24日", "ひらがな3カタカナ", "한글12 Seoul", "привет мир 5", "Ελλάδα2", " 漢字", "Montréal", "a,b", "...", "))", "---", "===", "-=-=", "</div>", "<br/>", "\ufffd", "😀😀", "e\u0301te\u0301", "漢\u0301字", "\u0301", "", " ", "\x00\x01",
]


def _hex(text: str) -> str:
    return text.encode().hex()


_FIXTURE_SQL = "[" + ", ".join(f"'{_hex(x)}'" for x in FIXTURES) + f"][doc_id % {len(FIXTURES)} + 1]"


@query(f"""SELECT doc_id, fixture, CAST(len(c) AS INT) AS chunks, md5(array_to_string(c, chr(1))) AS cut
    FROM (SELECT doc_id, fixture, regexp_extract_all(decode(unhex(fixture)) || chr(10) || coalesce(text, ''), '{PATTERN}') AS c FROM (SELECT doc_id, text, {_FIXTURE_SQL} AS fixture FROM documents))""")
def pretok_fixtures(spark, sf):
    """Each document's text behind one of the fixtures and a line end, cut as one text."""
    docs = t(spark, sf, "documents").withColumn("fixture", F.element_at(F.array(*map(F.lit, FIXTURES)), (F.pmod("doc_id", F.lit(len(FIXTURES))) + 1).cast("int")))
    c = pretokenize(F.concat("fixture", F.lit("\n"), F.coalesce("text", F.lit(""))))
    return docs.select("doc_id", F.lower(F.hex(F.encode("fixture", "UTF-8"))).alias("fixture"), c.alias("c")).select("doc_id", "fixture", F.size("c").alias("chunks"), F.md5(F.array_join("c", "\x01").cast("binary")).alias("cut"))


# surrounding operators


def op(name: str, sql: str, build):
    _Q[f"op_{name}"] = build
    _O[f"op_{name}"] = sql


op("s10_project", "SELECT doc_id, CAST(octet_length(encode(text)) AS INT) AS bytes, CAST(length(text) AS INT) AS chars FROM documents", lambda s, d: t(s, d, "documents").select("doc_id", F.octet_length("text").alias("bytes"), F.char_length("text").alias("chars")))
op("s11_filter", "SELECT doc_id FROM documents WHERE lang IN ('de', 'fr') AND source IS NOT DISTINCT FROM 'src0' AND n_chars BETWEEN 500 AND 2000", lambda s, d: t(s, d, "documents").filter(F.col("lang").isin("de", "fr") & F.col("source").eqNullSafe("src0") & F.col("n_chars").between(500, 2000)).select("doc_id"))
op("s12_pattern", "SELECT doc_id FROM documents WHERE regexp_matches(text, '[A-Za-z]+@[A-Za-z]+') OR text LIKE '%License%'", lambda s, d: t(s, d, "documents").filter(F.col("text").rlike("[A-Za-z]+@[A-Za-z]+") | F.col("text").like("%License%")).select("doc_id"))
op("s13_case", "SELECT CASE WHEN n_chars < 500 THEN 'short' WHEN n_chars < 5000 THEN 'middle' ELSE 'long' END AS band, count(*) AS n FROM documents GROUP BY 1", lambda s, d: t(s, d, "documents").groupBy(F.when(F.col("n_chars") < 500, "short").when(F.col("n_chars") < 5000, "middle").otherwise("long").alias("band")).agg(F.count("*").alias("n")))
op("s14_broadcast_join", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1", lambda s, d: t(s, d, "customer").join(F.broadcast(t(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n")))
_JOIN = "SELECT o_orderpriority, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"
op("s15_shuffled_hash_join", _JOIN, lambda s, d: t(s, d, "lineitem").join(t(s, d, "orders").hint("shuffle_hash"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n")))
op("s16_merge_join", _JOIN, lambda s, d: t(s, d, "lineitem").join(t(s, d, "orders").hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n")))
op("s17_full_outer", "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, coalesce(quality, -1) AS quality FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id", lambda s, d: t(s, d, "documents").select("doc_id").join(t(s, d, "labels").select("doc_id", "quality"), "doc_id", "full").na.fill(-1, ["quality"]))
op("s18_semi_anti", "SELECT (SELECT count(*) FROM documents SEMI JOIN labels USING (doc_id)) AS labelled, (SELECT count(*) FROM documents ANTI JOIN labels USING (doc_id)) AS bare", lambda s, d: t(s, d, "documents").join(t(s, d, "labels"), "doc_id", "left_semi").agg(F.count("*").alias("labelled")).crossJoin(t(s, d, "documents").join(t(s, d, "labels"), "doc_id", "left_anti").agg(F.count("*").alias("bare"))))
op("s20_range_join", "SELECT lo, count(*) AS n FROM documents JOIN (VALUES (0, 1000), (1000, 4000), (4000, 1000000)) b(lo, hi) ON n_chars >= lo AND n_chars < hi GROUP BY lo", lambda s, d: t(s, d, "documents").join(F.broadcast(s.createDataFrame([(0, 1000), (1000, 4000), (4000, 1000000)], "lo int, hi int")), (F.col("n_chars") >= F.col("lo")) & (F.col("n_chars") < F.col("hi"))).groupBy("lo").agg(F.count("*").alias("n")))
op("s22_interval_join", "SELECT count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR", lambda s, d: t(s, d, "events").filter("event_type = 'click'").alias("a").join(t(s, d, "events").filter("event_type = 'purchase'").alias("b"), F.expr("a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")).agg(F.count("*").alias("n")))
op("s25_hash_aggregate", "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY ALL", lambda s, d: t(s, d, "documents").groupBy("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars")))
op("s27_count_distinct", "SELECT lang, count(DISTINCT text) AS n FROM documents GROUP BY lang", lambda s, d: t(s, d, "documents").groupBy("lang").agg(F.count_distinct("text").alias("n")))
op("s29_cube", "SELECT lang, source, count(*) AS n, CAST(grouping_id(lang, source) AS BIGINT) AS g FROM documents GROUP BY CUBE (lang, source)", lambda s, d: t(s, d, "documents").cube("lang", "source").agg(F.count("*").alias("n"), F.grouping_id("lang", "source").alias("g")))
op("s30_quantiles", "SELECT lang, quantile_cont(n_chars, 0.5) AS median, max(n_chars) AS top FROM documents GROUP BY lang", lambda s, d: t(s, d, "documents").groupBy("lang").agg(F.percentile("n_chars", 0.5).alias("median"), F.max("n_chars").alias("top")))
op("s31_max_by", "SELECT lang, max(n_chars) AS top, min(doc_id) FILTER (WHERE n_chars = m) AS doc_id FROM (SELECT *, max(n_chars) OVER (PARTITION BY lang) AS m FROM documents) GROUP BY lang", lambda s, d: t(s, d, "documents").groupBy("lang").agg(F.max("n_chars").alias("top"), F.max_by("doc_id", F.struct("n_chars", -F.col("doc_id"))).alias("doc_id")))
op("s32_count_if", "SELECT lang, count(*) FILTER (WHERE quality = 1) AS good, count(*) FILTER (WHERE toxic = 1) AS toxic FROM documents JOIN labels USING (doc_id) GROUP BY lang", lambda s, d: t(s, d, "documents").join(t(s, d, "labels"), "doc_id").groupBy("lang").agg(F.count_if(F.col("quality") == 1).alias("good"), F.count_if(F.col("toxic") == 1).alias("toxic")))
op("s33_pivot", "SELECT source, count(*) FILTER (WHERE lang = 'de') AS de, count(*) FILTER (WHERE lang = 'en') AS en FROM documents GROUP BY source", lambda s, d: t(s, d, "documents").groupBy("source").pivot("lang", ["de", "en"]).count().na.fill(0))
op("s34_ranking", "SELECT doc_id, CAST(row_number() OVER w AS INT) AS r, CAST(ntile(4) OVER w AS INT) AS q FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars, doc_id)", lambda s, d: t(s, d, "documents").select("doc_id", F.row_number().over(Window.partitionBy("lang").orderBy("n_chars", "doc_id")).alias("r"), F.ntile(4).over(Window.partitionBy("lang").orderBy("n_chars", "doc_id")).alias("q")))
op("s36_offsets", "SELECT doc_id, lag(n_chars, 1, -1) OVER w AS before, lead(n_chars, 1, -1) OVER w AS after FROM documents WINDOW w AS (PARTITION BY source ORDER BY doc_id)", lambda s, d: t(s, d, "documents").select("doc_id", F.lag("n_chars", 1, -1).over(Window.partitionBy("source").orderBy("doc_id")).alias("before"), F.lead("n_chars", 1, -1).over(Window.partitionBy("source").orderBy("doc_id")).alias("after")))
op("s38_moving_sum", "SELECT doc_id, CAST(sum(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS 2 PRECEDING) AS BIGINT) AS s FROM documents", lambda s, d: t(s, d, "documents").select("doc_id", F.sum("n_chars").over(Window.partitionBy("source").orderBy("doc_id").rowsBetween(-2, 0)).alias("s")))
op("s40_top_k", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 10", lambda s, d: t(s, d, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(10))
op("s43_sets", "SELECT count(*) AS n FROM (SELECT source FROM documents WHERE lang = 'en' INTERSECT SELECT source FROM documents WHERE lang = 'de')", lambda s, d: t(s, d, "documents").filter("lang = 'en'").select("source").intersect(t(s, d, "documents").filter("lang = 'de'").select("source")).agg(F.count("*").alias("n")))
op("s48_json", "SELECT json_extract_string(props, '$.k') AS k, count(*) AS n FROM events GROUP BY 1", lambda s, d: t(s, d, "events").groupBy(F.get_json_object("props", "$.k").alias("k")).agg(F.count("*").alias("n")))
op("s49_dates", "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS n FROM orders GROUP BY 1", lambda s, d: t(s, d, "orders").groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month")).agg(F.count("*").alias("n")))
op("s51_subquery", "SELECT lang, round(100.0 * sum(n_chars) / (SELECT sum(n_chars) FROM documents), 4) AS share FROM documents GROUP BY lang", lambda s, d: (t(s, d, "documents").createOrReplaceTempView("sw_docs"), s.sql("SELECT lang, round(CAST(100.0 AS DOUBLE) * sum(n_chars) / (SELECT sum(n_chars) FROM sw_docs), 4) AS share FROM sw_docs GROUP BY lang"))[1])


def asof(s, d):
    """The version in force at each event: versions and events in one ordered union, the last version carried on."""
    versions = s.createDataFrame([("2024-01-01", 1), ("2024-01-11", 2), ("2024-01-21", 3)], "since string, version int").select(F.col("since").cast("timestamp_ntz").alias("ts"), "version", F.lit(None).cast("long").alias("event_id"))
    events = t(s, d, "events").select("ts", F.lit(None).cast("int").alias("version"), "event_id", F.to_date("ts").alias("day"))
    # a version applies to every day until the next: days join the versions by range, and only a day's own change needs the order
    days = events.select("day").distinct()
    carried = days.join(F.broadcast(versions.select(F.col("ts").alias("since"), F.col("version").alias("v"))), F.col("since") <= F.col("day") + F.expr("INTERVAL 1 DAY")).select("day", "since", "v")
    got = events.join(carried, "day", "left").groupBy("event_id").agg(F.max_by("v", F.when(F.col("since") <= F.col("ts"), F.col("since"))).alias("version"))
    return got


op("s21_asof_join", "SELECT event_id, version FROM events e ASOF LEFT JOIN (VALUES (TIMESTAMP '2024-01-01', 1), (TIMESTAMP '2024-01-11', 2), (TIMESTAMP '2024-01-21', 3)) v(since, version) ON e.ts >= v.since", asof)
op("s19_theta_join", "SELECT tau, count(*) AS n FROM part CROSS JOIN (VALUES (10), (20), (30)) x(tau) WHERE p_size < tau GROUP BY tau", lambda s, d: t(s, d, "part").join(F.broadcast(s.createDataFrame([(10,), (20,), (30,)], "tau int")), F.col("p_size") < F.col("tau")).groupBy("tau").agg(F.count("*").alias("n")))
op("s23_self_join", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey", lambda s, d: t(s, d, "nation").alias("a").join(t(s, d, "nation").alias("b"), F.expr("a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b")))
op("s24_lateral", "SELECT p_partkey, unnest(string_split(p_name, ' ')) AS word FROM part", lambda s, d: t(s, d, "part").select("p_partkey", F.explode(F.split("p_name", " ")).alias("word")))
op("s26_sort_aggregate", "SELECT source, string_agg(CAST(doc_id AS VARCHAR), ',' ORDER BY doc_id) AS ids FROM documents GROUP BY source", lambda s, d: t(s, d, "documents").groupBy("source").agg(F.array_sort(F.collect_list("doc_id")).alias("i")).select("source", F.array_join(F.transform("i", lambda x: x.cast("string")), ",").alias("ids")))
_Q["op_s28_approx_distinct"] = lambda s, d: t(s, d, "documents").select(F.explode(pretokenize(F.col("text"))).alias("c")).agg(F.approx_count_distinct("c", 0.02).alias("chunks"))
op("s33_unpivot", "SELECT doc_id, 'quality' AS what, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels", lambda s, d: t(s, d, "labels").unpivot("doc_id", ["quality", "toxic"], "what", "value"))
op("s35_running_sum", "SELECT l_orderkey, l_linenumber, sum(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity ROWS UNBOUNDED PRECEDING) AS q FROM lineitem", lambda s, d: t(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.sum("l_quantity").over(Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity").rowsBetween(Window.unboundedPreceding, 0)).alias("q")))
op("s37_range_frame", "SELECT doc_id, count(*) OVER (PARTITION BY lang ORDER BY n_chars RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS near FROM documents", lambda s, d: t(s, d, "documents").select("doc_id", F.count("*").over(Window.partitionBy("lang").orderBy("n_chars").rangeBetween(-100, 100)).alias("near")))
op("s39_sort_nulls", "SELECT doc_id, CAST(row_number() OVER (ORDER BY quality DESC NULLS LAST, doc_id) AS INT) AS r FROM documents LEFT JOIN labels USING (doc_id) ORDER BY r LIMIT 50", lambda s, d: (lambda x: x.select("doc_id", F.row_number().over(Window.partitionBy(F.lit(1)).orderBy(F.desc_nulls_last("quality"), "doc_id")).alias("r")))(t(s, d, "documents").join(t(s, d, "labels"), "doc_id", "left").orderBy(F.desc_nulls_last("quality"), "doc_id").limit(50)))
op("s41_top_k_per_group", "SELECT lang, doc_id FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 3", lambda s, d: t(s, d, "documents").select("lang", "doc_id", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id")).alias("r")).filter("r <= 3").drop("r"))
op("s42_limit_offset", "SELECT doc_id FROM documents ORDER BY doc_id LIMIT 7 OFFSET 5", lambda s, d: t(s, d, "documents").select("doc_id").orderBy("doc_id").offset(5).limit(7))
op("s44_strings", "SELECT doc_id, upper(hex(encode(substr(text, 1, 8)))) AS h, translate(source, 'src', 'SRC') AS s FROM documents", lambda s, d: t(s, d, "documents").select("doc_id", F.hex(F.encode(F.substring("text", 1, 8), "UTF-8")).alias("h"), F.translate("source", "src", "SRC").alias("s")))
op("s45_math", "SELECT doc_id, CAST(ceil(n_chars / 7) AS BIGINT) AS c, CAST(n_chars % 7 AS BIGINT) AS m FROM documents", lambda s, d: t(s, d, "documents").select("doc_id", F.ceil(F.col("n_chars") / 7).alias("c"), F.pmod("n_chars", F.lit(7)).alias("m")))
op("s46_arrays", "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INT) AS positive FROM embeddings", lambda s, d: t(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive")))
op("s47_maps", "SELECT lang, count(*) FILTER (WHERE source = 'src0') AS first FROM documents GROUP BY lang", lambda s, d: t(s, d, "documents").groupBy("lang", "source").count().groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("source", "count"))).alias("m")).select("lang", F.coalesce(F.element_at("m", F.lit("src0")), F.lit(0)).alias("first")))
_DOUBLING = """WITH RECURSIVE r AS (SELECT 1 AS n, CAST(1 AS BIGINT) AS f UNION ALL SELECT n + 1, f * 2 FROM r WHERE f * 2 <= (SELECT max(c_custkey) FROM {customer}))
    SELECT /*+ BROADCAST(r) */ n, f, count(*) AS keys FROM r JOIN {customer} ON c_custkey >= f AND c_custkey < f * 2 GROUP BY n, f"""
op("s50_recursive", _DOUBLING.format(customer="customer"), lambda s, d: s.sql(_DOUBLING, customer=t(s, d, "customer")))

# streams


op("st_tumbling", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL", lambda s, d: streams.run_to_end(streams.tumbling(streams.table_stream(s, d, "events")), "complete"))
op("st_dedup", "SELECT DISTINCT event_id, event_type FROM events", lambda s, d: streams.run_to_end(streams.deduplicated(streams.table_stream(s, d, "events"))))
op("st_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey", lambda s, d: streams.run_to_end(streams.with_customers(streams.table_stream(s, d, "events"), t(s, d, "customer"))))
op("st_sliding", "SELECT time_bucket(INTERVAL 15 MINUTE, ts) - i * INTERVAL 15 MINUTE AS start, event_type, count(*) AS n FROM events, (SELECT unnest(range(0, 4)) AS i) GROUP BY ALL", lambda s, d: streams.run_to_end(streams.tumbling(streams.table_stream(s, d, "events"), "1 hour", "15 minutes"), "complete"))


op("st_sessions", """SELECT min(ts) AS start, user_id, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s
    FROM (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""", lambda s, d: streams.run_to_end(streams.sessions(streams.table_stream(s, d, "events")), "complete"))
op("st_stream_pairs", "SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR", lambda s, d: streams.run_to_end(streams.stream_pairs(streams.table_stream(s, d, "events"), streams.table_stream(s, d, "events"))))
op("st_exposure", STATE_SQL + f""", {ITEMS_SQL} SELECT CAST(id AS INT) AS id, count(*) AS n FROM (SELECT unnest(flatten(list_transform(string_split(sym, ''), lambda c: e[unicode(c) + 1]))) AS id FROM occ JOIN enc USING (chunk) JOIN last ON step = k) GROUP BY ALL""", lambda s, d: streams.run_to_end(streams.running_exposure(streams.table_stream(s, d, "benchmark"), vp(s, d)[1], "item_id"), "complete"))


@query()
def st_encode(spark, sf):
    s = workloads.study(spark, sf)
    return streams.run_to_end(streams.encode_stream(streams.table_stream(spark, sf, "documents"), s.tokenizer("AB", s.budgets[0], "0.4")))


def queries() -> dict:
    return dict(_Q)


def oracle_sql() -> dict[str, str]:
    return dict(_O)
