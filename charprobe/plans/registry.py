"""All registered queries of the reference's methods, each with its DuckDB twin where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import streaming
from ..functions import fixed_width, length_class
from ..operators import corpus, encode, measure, probe, rewrite, stats, tokenize, vocab
from ..sources import spread, table
from . import experiments

SEED = 42
WORDS_IN_VOCAB = 2000

_spark: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_sql: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        _spark[f.__name__] = f
        if sql is not None:
            _sql[f.__name__] = sql
        return f

    return add


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(_spark)


def oracle_sql() -> dict[str, str]:
    return dict(_sql)


# -- shared parts ------------------------------------------------------------------------------------------------


def english(s: SparkSession, d: str) -> DataFrame:
    return spread(table(s, d, "documents").where("lang = 'en'").select("doc_id", "text"), "doc_id")


def words(s: SparkSession, d: str) -> DataFrame:
    return corpus.words(english(s, d))


def chunks(s: SparkSession, d: str) -> DataFrame:
    return tokenize.fixed_width_tokens(words(s, d))


def word_vocab(s: SparkSession, d: str) -> DataFrame:
    return vocab.build(words(s, d).select(F.col("word").alias("surface"), "has_space"), WORDS_IN_VOCAB)


def labels(s: SparkSession, d: str) -> DataFrame:
    return probe.label(vocab.target_vocab(word_vocab(s, d)))


def matched(s: SparkSession, d: str) -> DataFrame:
    return probe.sample_matched(labels(s, d), SEED)


RE_WORD = r"'[ \t\n\r]?[A-Za-z]+'"
WORDS = rf"""found AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), {RE_WORD}) AS w FROM documents WHERE lang = 'en'),
raw AS (SELECT doc_id, generate_subscripts(w, 1) - 1 AS pos, unnest(w) AS m FROM found),
words AS MATERIALIZED (SELECT doc_id, pos, lower(regexp_replace(m, '^[ \t\n\r]', '')) AS word, regexp_matches(m, '^[ \t\n\r]') AS has_space FROM raw),
counts AS MATERIALIZED (SELECT word, has_space, count(*) AS freq FROM words GROUP BY ALL)"""
CHUNKS = WORDS + """,
pieces AS (SELECT doc_id, pos, has_space, regexp_extract_all(word, '.{1,3}') AS p FROM words),
cut AS (SELECT doc_id, pos AS word_pos, has_space, generate_subscripts(p, 1) - 1 AS sub_pos, unnest(p) AS surface FROM pieces),
tokens AS MATERIALIZED (SELECT doc_id, word_pos, sub_pos, surface, has_space AND sub_pos = 0 AS has_space, length(surface) AS n_letters FROM cut)"""
VOCAB = WORDS + f""",
best AS (SELECT word AS surface, has_space, freq FROM counts ORDER BY freq DESC, word, has_space LIMIT {WORDS_IN_VOCAB}),
vocab AS MATERIALIZED (SELECT row_number() OVER (ORDER BY freq DESC, surface, has_space) - 1 AS token_id, surface, has_space, length(surface) AS n_letters, freq FROM best)"""
LABELS = VOCAB + """,
letters AS (SELECT chr(97 + i::INT) AS letter FROM range(26) t(i)),
labels AS MATERIALIZED (SELECT letter, token_id, surface, has_space, n_letters, (position(letter IN surface) > 0)::INT AS y FROM vocab, letters)"""


def draw_sql(*parts: str) -> str:
    return f"('0x' || substr(md5({key_sql(*parts)}), 1, 8))::BIGINT"


def key_sql(*parts: str) -> str:
    return f"concat_ws('|', '{SEED}', {', '.join(parts)})"


MATCHED = LABELS + f""",
k AS (SELECT letter, n_letters, least(sum(y), sum(1 - y)) AS k FROM labels GROUP BY ALL),
ranked AS (SELECT *, row_number() OVER (PARTITION BY letter, n_letters, y ORDER BY md5({key_sql('letter', 'token_id')}), token_id) AS pair_no FROM labels),
matched AS MATERIALIZED (SELECT r.* FROM ranked r JOIN k USING (letter, n_letters) WHERE pair_no <= k)"""


def sql(base: str, select: str) -> str:
    return f"WITH {base}\n{select}"


# -- words and tokens --------------------------------------------------------------------------------------------


@query(sql(WORDS, "SELECT doc_id, pos::INT AS pos, word, has_space::INT AS spaced FROM words"))
def words_all(s, d):
    return words(s, d).select("doc_id", "pos", "word", F.col("has_space").cast("int").alias("spaced"))


@query(sql(WORDS, "SELECT word, has_space::INT AS spaced, freq FROM counts"))
def word_counts(s, d):
    return corpus.word_counts(words(s, d)).select("word", F.col("has_space").cast("int").alias("spaced"), "freq")


@query(sql(VOCAB, "SELECT token_id, surface, has_space::INT AS spaced, n_letters, freq FROM vocab"))
def word_vocab_topk(s, d):
    return word_vocab(s, d).select("token_id", "surface", F.col("has_space").cast("int").alias("spaced"), "n_letters", "freq")


@query(sql(VOCAB, "SELECT doc_id, count(*) AS tokens, sum((token_id IS NULL)::INT)::BIGINT AS unknown FROM words LEFT JOIN vocab ON word = surface AND words.has_space = vocab.has_space GROUP BY doc_id"))
def word_tokens_unk(s, d):
    t = tokenize.whitespace_tokens(words(s, d), word_vocab(s, d))
    return t.groupBy("doc_id").agg(F.count("*").alias("tokens"), F.sum((F.col("token_id") < 0).cast("int")).alias("unknown"))


@query(sql(CHUNKS, "SELECT doc_id, word_pos::INT AS word_pos, sub_pos::INT AS sub_pos, surface, has_space::INT AS spaced, n_letters FROM tokens"))
def fixed_width_tokens(s, d):
    return chunks(s, d).select("doc_id", "word_pos", "sub_pos", "surface", F.col("has_space").cast("int").alias("spaced"), "n_letters")


@query(sql(CHUNKS, "SELECT row_number() OVER (ORDER BY count(*) DESC, surface, has_space) - 1 AS token_id, surface, has_space::INT AS spaced, length(surface) AS n_letters, count(*) AS freq FROM tokens GROUP BY surface, has_space"))
def fixed_width_vocab(s, d):
    return vocab.build(chunks(s, d)).select("token_id", "surface", F.col("has_space").cast("int").alias("spaced"), "n_letters", "freq")


@query(sql(WORDS, "SELECT doc_id, count(*) AS words, sum(length(word))::BIGINT AS letters, min(word) AS least, max(word) AS greatest FROM words GROUP BY doc_id"))
def decode_roundtrip(s, d):
    return tokenize.decode(chunks(s, d)).groupBy("doc_id").agg(F.count("*").alias("words"), F.sum(F.length("word")).alias("letters"), F.min("word").alias("least"), F.max("word").alias("greatest"))


@query(sql(CHUNKS, "SELECT count(DISTINCT (doc_id, word_pos)) AS words, count(*) AS tokens, round(count(*) / count(DISTINCT (doc_id, word_pos)), 6) AS tokens_per_word FROM tokens"))
def tokenizer_stats(s, d):
    return tokenize.tokenizer_stats(chunks(s, d))


@query("WITH w AS (SELECT regexp_extract_all(p_name, '[ ]?[A-Za-z]+') AS m FROM part), u AS (SELECT unnest(m) AS m FROM w) SELECT lower(trim(m)) AS word, count(*) AS freq FROM u GROUP BY ALL")
def part_name_words(s, d):
    return corpus.words(table(s, d, "part"), "p_partkey", "p_name").groupBy("word").agg(F.count("*").alias("freq"))


@query(rf"WITH w AS (SELECT role, regexp_extract_all(coalesce(text, ''), {RE_WORD}) AS m FROM conversations), u AS (SELECT role, lower(regexp_replace(unnest(m), '^[ \t\n\r]', '')) AS word FROM w) SELECT role, count(*) AS words, sum((length(word) + 2) // 3)::BIGINT AS tokens FROM u GROUP BY role")
def conversation_tokens_by_role(s, d):
    c = table(s, d, "conversations").select("role", F.explode(corpus.word_array(F.col("text"))).alias("w"))
    return c.groupBy("role").agg(F.count("*").alias("words"), F.sum(F.size(fixed_width(F.col("w.word")))).alias("tokens"))


@query()
def html_text(s, d):
    return table(s, d, "pages").select("page_id", corpus.html_text(F.col("html")).alias("text"))


@query("SELECT d.doc_id, n_chars FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND quality >= 1)")
def quality_semijoin(s, d):
    return corpus.quality_docs(table(s, d, "documents"), table(s, d, "labels")).select("doc_id", "n_chars")


@query("SELECT min(doc_id) AS doc_id FROM documents GROUP BY coalesce(text, '')")
def dedup_exact(s, d):
    return corpus.exact_copies_dropped(table(s, d, "documents")).select("doc_id")


LOWERED = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
RUNS = rf"""runs_of AS (SELECT id, unnest([array_to_string(w[i:i + 12], chr(1)) for i in range(1, len(w) - 11)]) AS run FROM (SELECT id, regexp_extract_all({LOWERED}, '[^\x20\x09-\x0D]+') AS w FROM texts) WHERE len(w) >= 13)"""


@query(f"WITH texts AS (SELECT 'd' || doc_id AS id, text FROM documents UNION ALL SELECT 'b' || item_id, text FROM benchmark), {RUNS}, bad AS (SELECT DISTINCT id FROM runs_of WHERE id[1] = 'd' AND run IN (SELECT run FROM runs_of WHERE id[1] = 'b')) SELECT doc_id FROM documents WHERE 'd' || doc_id NOT IN (SELECT id FROM bad)")
def benchmark_antijoin(s, d):
    return corpus.without_benchmark(spread(table(s, d, "documents").select("doc_id", "text"), "doc_id"), table(s, d, "benchmark")).select("doc_id")


# -- the probe's examples ----------------------------------------------------------------------------------------


@query(sql(VOCAB, "SELECT token_id, surface, n_letters FROM vocab WHERE regexp_matches(surface, '^[A-Za-z]+$')"))
def target_vocab(s, d):
    return vocab.target_vocab(word_vocab(s, d)).select("token_id", "surface", "n_letters")


@query(sql(LABELS, "SELECT token_id, surface, sum(y * (1 << (ascii(letter) - 97)))::INT AS letter_mask FROM labels GROUP BY ALL"))
def letter_mask(s, d):
    return vocab.with_mask(word_vocab(s, d)).select("token_id", "surface", "letter_mask")


@query(sql(LABELS, "SELECT letter, token_id, n_letters, y FROM labels"))
def letter_labels(s, d):
    return labels(s, d).select("letter", "token_id", "n_letters", "y")


@query(sql(LABELS, "SELECT letter, n_letters, sum(y)::BIGINT AS n_pos, sum(1 - y)::BIGINT AS n_neg, least(sum(y), sum(1 - y))::BIGINT AS k FROM labels GROUP BY ALL"))
def strata_counts(s, d):
    return probe.strata(labels(s, d), ["n_letters"])


@query(sql(MATCHED, "SELECT letter, token_id, n_letters, y, pair_no::INT AS pair_no FROM matched"))
def matched_sample(s, d):
    return matched(s, d).select("letter", "token_id", "n_letters", "y", "pair_no")


@query(sql(LABELS + f""", k AS (SELECT letter, least(sum(y), sum(1 - y)) AS k FROM labels GROUP BY ALL),
ranked AS (SELECT *, row_number() OVER (PARTITION BY letter, y ORDER BY md5({key_sql('letter', 'token_id')}), token_id) AS pair_no FROM labels)""", "SELECT letter, token_id, n_letters, y, pair_no::INT AS pair_no FROM ranked JOIN k USING (letter) WHERE pair_no <= k"))
def unmatched_sample(s, d):
    return probe.sample_unmatched(labels(s, d), SEED).select("letter", "token_id", "n_letters", "y", "pair_no")


PAIR = "concat_ws('/', letter, n_letters, pair_no)"


@query(sql(MATCHED, f"SELECT letter, token_id, y, ({draw_sql(PAIR)} % 1000 < 200)::INT AS is_test FROM matched"))
def pair_split(s, d):
    return probe.split_pairs(matched(s, d), 0.2, SEED).select("letter", "token_id", "y", "is_test")


@query(sql(MATCHED, f"SELECT letter, token_id, y, ({draw_sql(PAIR)} % 5)::INT AS fold FROM matched"))
def random_folds(s, d):
    return probe.random_folds(matched(s, d), 5, SEED).select("letter", "token_id", "y", "fold")


LENGTH_ONLY = """per AS (SELECT letter, n_letters, sum(y) AS p, sum(1 - y) AS q FROM {t} GROUP BY ALL),
ups AS (SELECT letter, sum(p) OVER w - coalesce(sum(p) OVER b, 0) + coalesce(sum(q) OVER b, 0) AS up, sum(p + q) OVER w AS n FROM per WINDOW w AS (PARTITION BY letter), b AS (PARTITION BY letter ORDER BY n_letters ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))
SELECT letter, max(n)::BIGINT AS n, round(100 * max(greatest(up, n - up, n / 2)) / max(n), 6) AS length_accuracy FROM ups GROUP BY letter"""


@query(f"WITH {MATCHED}, " + LENGTH_ONLY.format(t="matched"))
def length_only_accuracy(s, d):
    return measure.length_only_accuracy(matched(s, d))


@query(f"WITH {LABELS}, " + LENGTH_ONLY.format(t="labels"))
def length_only_accuracy_unbalanced(s, d):
    return measure.length_only_accuracy(labels(s, d))


@query(sql(VOCAB, "SELECT surface, has_space::INT AS spaced, least(greatest(n_letters, 3), 7)::INT AS length_class FROM vocab"))
def length_classes(s, d):
    return word_vocab(s, d).select("surface", F.col("has_space").cast("int").alias("spaced"), length_class(F.col("n_letters")).alias("length_class"))


@query(sql(VOCAB, "SELECT least(greatest(n_letters, 3), 7)::INT AS length_class, count(*) AS entries, round(100 * count(*) / sum(count(*)) OVER (), 6) AS share FROM vocab GROUP BY 1"))
def vocab_share(s, d):
    return measure.vocab_share(word_vocab(s, d))


@query(sql(WORDS, "SELECT length(word) AS n_letters, count(DISTINCT word) AS types, sum(freq)::BIGINT AS occurrences, round(sum(freq) / count(DISTINCT word), 9) AS mean_freq FROM counts GROUP BY 1"))
def length_frequency(s, d):
    return stats.length_frequency(corpus.word_counts(words(s, d)))


@query(sql(LABELS + ", t AS (SELECT g, p FROM (VALUES (true), (false)) a(g), (VALUES (1), (2), (3)) b(p))", "SELECT letter, g::INT AS spaced, p AS group_pos, sum(y)::BIGINT AS positives, sum(1 - y)::BIGINT AS negatives FROM labels, t WHERE has_space = g AND (y = 0 OR position(letter IN surface) = p) GROUP BY ALL"))
def position_groups(s, d):
    g = probe.position_groups(labels(s, d))
    return g.groupBy("letter", F.col("group_space").cast("int").alias("spaced"), "group_pos").agg(F.sum("y").alias("positives"), F.sum(1 - F.col("y")).alias("negatives"))


@query(sql(MATCHED, "SELECT coalesce(has_space::INT, -1) AS spaced, count(*) AS n, sum(y)::BIGINT AS positives FROM matched GROUP BY GROUPING SETS ((has_space), ())"))
def space_groups(s, d):
    m = matched(s, d).withColumn("spaced", F.col("has_space").cast("int"))
    return m.groupingSets([["spaced"], []], "spaced").agg(F.count("*").alias("n"), F.sum("y").alias("positives")).select(F.coalesce("spaced", F.lit(-1)).alias("spaced"), "n", "positives")


CONTEXT = {"prev": "CASE WHEN position(letter IN surface) = 1 THEN '^' ELSE substr(surface, position(letter IN surface) - 1, 1) END", "next": "CASE WHEN position(letter IN surface) = length(surface) THEN '$' ELSE substr(surface, position(letter IN surface) + 1, 1) END"}


@query(sql(LABELS, f"SELECT letter, {CONTEXT['prev']} AS grp, count(*) AS n FROM labels WHERE y = 1 GROUP BY ALL"))
def context_prev(s, d):
    return probe.context(labels(s, d), "prev").where("y = 1").groupBy("letter", "grp").agg(F.count("*").alias("n"))


@query(sql(LABELS, f"SELECT letter, {CONTEXT['next']} AS grp, count(*) AS n FROM labels WHERE y = 1 GROUP BY ALL"))
def context_next(s, d):
    return probe.context(labels(s, d), "next").where("y = 1").groupBy("letter", "grp").agg(F.count("*").alias("n"))


@query(sql(LABELS + f""", g AS (SELECT letter, {CONTEXT['prev']} AS grp, count(*) AS n FROM labels WHERE y = 1 GROUP BY ALL),
o AS (SELECT *, row_number() OVER (PARTITION BY letter ORDER BY n DESC, grp) - 1 AS place FROM g)""", "SELECT letter, grp, n, (CASE WHEN (place // 5) % 2 = 0 THEN place % 5 ELSE 4 - place % 5 END)::INT AS fold FROM o"))
def group_folds_serpentine(s, d):
    return probe.group_folds(labels(s, d), 5, "prev", "serpentine")


@query()
def group_folds_greedy(s, d):
    return probe.group_folds(labels(s, d), 5, "prev", "greedy")


@query(sql(VOCAB + ", p AS (SELECT * FROM (VALUES ('tion', 'end'), ('er', 'any'), ('th', 'start'), ('ing', 'end')) v(pattern, place))", "SELECT pattern, place, count(*) AS tokens, sum((CASE place WHEN 'start' THEN starts_with(surface, pattern) WHEN 'end' THEN ends_with(surface, pattern) ELSE contains(surface, pattern) END)::INT)::BIGINT AS positives FROM vocab, p GROUP BY ALL"))
def substring_labels(s, d):
    rows = probe.label_substrings(word_vocab(s, d), [("tion", "end"), ("er", "any"), ("th", "start"), ("ing", "end")])
    return rows.groupBy("pattern", "place").agg(F.count("*").alias("tokens"), F.sum("y").alias("positives"))


def _pick(what: str, modulo: str) -> str:
    return f"({draw_sql(repr(what), 'surface')} % {modulo})"


@query(sql(VOCAB + f""", v AS (SELECT token_id, surface, length(surface) AS n, substr('abcdefghijklmnopqrstuvwxyz', {_pick('letter', '26')} + 1, 1) AS l, {_pick('at', 'length(surface)')} + 1 AS a, {_pick('swap', '(length(surface) - 1)')} + 1 AS i FROM vocab WHERE length(surface) >= 2)""", """SELECT token_id, surface, 'contains' AS task, l AS argument, (position(l IN surface) > 0)::INT::VARCHAR AS answer FROM v
UNION ALL SELECT token_id, surface, 'insert', l || '@' || a, left(surface, a - 1) || l || substr(surface, a) FROM v
UNION ALL SELECT token_id, surface, 'delete', a::VARCHAR, left(surface, a - 1) || substr(surface, a + 1) FROM v
UNION ALL SELECT token_id, surface, 'swap', i::VARCHAR, left(surface, i - 1) || substr(surface, i + 1, 1) || substr(surface, i, 1) || substr(surface, i + 2) FROM v"""))
def composition_tasks(s, d):
    return probe.composition_tasks(word_vocab(s, d), SEED)


@query(sql(CHUNKS + f", a AS (SELECT DISTINCT surface FROM tokens), b AS (SELECT word AS surface FROM counts GROUP BY word)", "SELECT (SELECT count(*) FROM a JOIN b USING (surface)) AS shared, (SELECT count(*) FROM a WHERE surface NOT IN (SELECT surface FROM b)) AS only_a, (SELECT count(*) FROM b WHERE surface NOT IN (SELECT surface FROM a)) AS only_b"))
def vocab_setops(s, d):
    return vocab.shared_and_own(chunks(s, d), words(s, d).select(F.col("word").alias("surface")))


# -- measures ----------------------------------------------------------------------------------------------------

#: An arithmetic stand-in for a probe, so that the measures have a twin: right unless a draw says otherwise.
STAND_IN = f"guess AS (SELECT letter, token_id, n_letters, y, ({draw_sql(repr('p'), 'letter', 'token_id')} % 3 > 0)::INT AS correct FROM matched)"


def stand_in(s, d):
    from ..functions import draw

    return matched(s, d).withColumn("correct", (draw(SEED, F.lit("p"), F.col("letter"), F.col("token_id")) % 3 > 0).cast("int"))


@query(sql(MATCHED + ", " + STAND_IN, "SELECT coalesce(letter, '*') AS letter, count(*) AS n, sum(correct)::BIGINT AS correct, round(100 * sum(correct) / count(*), 6) AS accuracy FROM guess GROUP BY ROLLUP (letter)"))
def micro_accuracy(s, d):
    return measure.accuracy_by_letter_and_all(stand_in(s, d))


@query(sql(MATCHED + ", " + STAND_IN, "SELECT round(avg(a), 6) AS macro_accuracy FROM (SELECT round(100 * sum(correct) / count(*), 6) AS a FROM guess GROUP BY letter)"))
def macro_accuracy(s, d):
    return measure.macro_accuracy(stand_in(s, d))


@query(sql(MATCHED + ", " + STAND_IN, "SELECT least(greatest(n_letters, 3), 7)::INT AS length_class, count(*) AS n, sum(correct)::BIGINT AS correct, round(100 * sum(correct) / count(*), 6) AS accuracy FROM guess GROUP BY 1"))
def accuracy_by_length(s, d):
    return measure.accuracy_by_length(stand_in(s, d))


@query(sql(MATCHED + ", " + STAND_IN + ", sizes AS (SELECT letter, count(*) AS n FROM guess GROUP BY letter), rarest AS (SELECT letter FROM sizes ORDER BY n, letter LIMIT 1)", "SELECT letter, count(*) AS n, sum(correct)::BIGINT AS correct, round(100 * sum(correct) / count(*), 6) AS accuracy FROM guess WHERE letter = (SELECT letter FROM rarest) GROUP BY letter"))
def one_letter_accuracy(s, d):
    """The report on one letter alone: that with the fewest examples."""
    rows = stand_in(s, d)
    rarest = rows.groupBy("letter").agg(F.count("*").alias("n")).orderBy("n", "letter").limit(1).select("letter")
    return measure.accuracy(rows.join(F.broadcast(rarest), "letter"), ["letter"]).select("letter", "n", "correct", "accuracy")


@query(sql(CHUNKS, "SELECT 1280::BIGINT AS sequences, 1310720::BIGINT AS tokens_per_step, 13107200000::BIGINT AS tokens, 13107200000::BIGINT - count(*) AS repeated FROM tokens"))
def token_budget(s, d):
    """The sample is the tokens of the documents."""
    return measure.token_budget(s, chunks(s, d).agg(F.count("*").alias("sample")))


@query("SELECT event_id, event_id % 10001 AS step, round(CASE WHEN event_id % 10001 < 2000 THEN 6e-4::DOUBLE * (event_id % 10001) / 2000 ELSE 6e-4::DOUBLE * 0.5 * (1 + cos(3.141592653589793 * least((event_id % 10001 - 2000) / 8000.0::DOUBLE, 1.0))) END, 12) AS rate FROM events")
def lr_schedule(s, d):
    """An event is a step; the schedule begins anew after its last step."""
    step = F.col("event_id") % 10001
    return table(s, d, "events").select("event_id", step.alias("step"), F.round(measure.learning_rate(step), 12).alias("rate"))


# -- merges and boundaries ---------------------------------------------------------------------------------------

STAGED_VOCAB = """one AS (SELECT chr(97 + i::INT) AS c FROM range(26) t(i)),
strings AS (SELECT c AS surface, 1 AS n_letters FROM one UNION ALL SELECT a.c || b.c, 2 FROM one a, one b UNION ALL SELECT a.c || b.c || d.c, 3 FROM one a, one b, one d),
staged AS (SELECT surface, g AS has_space, n_letters FROM strings, (VALUES (true), (false)) v(g))"""
MERGES = STAGED_VOCAB + f""",
spelled AS (SELECT (CASE WHEN has_space THEN 2 * n_letters - 1 ELSE 2 * n_letters - 2 END)::INT AS stage, (CASE WHEN has_space THEN ' ' ELSE '' END) || surface AS merged FROM staged),
halves AS (SELECT stage, left(merged, (length(merged) + 1) // 2) AS l, substr(merged, (length(merged) + 1) // 2 + 1) AS r, merged FROM spelled WHERE length(merged) >= 2),
merges AS MATERIALIZED (SELECT row_number() OVER (ORDER BY stage, md5({key_sql('stage', 'l', 'r')}), l, r) - 1 AS rank, * FROM halves),
strength AS (SELECT l, r, 677 - row_number() OVER (ORDER BY rank) AS strength FROM merges WHERE length(l) = 1 AND length(r) = 1 AND l <> ' ')"""
BOUNDARY = """near AS (SELECT surface, lead(surface) OVER (PARTITION BY doc_id, word_pos ORDER BY sub_pos) AS nxt FROM tokens),
boundary AS MATERIALIZED (SELECT right(surface, 1) AS last, left(nxt, 1) AS first, count(*) AS freq FROM near WHERE nxt IS NOT NULL GROUP BY ALL),
letters_in AS (SELECT surface, unnest(range(1, length(surface))) AS i FROM tokens WHERE length(surface) > 1),
inside AS MATERIALIZED (SELECT substr(surface, i, 1) AS last, substr(surface, i + 1, 1) AS first, count(*) AS freq FROM letters_in GROUP BY ALL)"""


#: The same over the letters of the documents' own words.
OWN_VOCAB = WORDS + ", " + STAGED_VOCAB.replace("SELECT chr(97 + i::INT) AS c FROM range(26) t(i)", "SELECT DISTINCT unnest(string_split(word, '')) AS c FROM counts")
OWN_MERGES = MERGES.replace(STAGED_VOCAB, OWN_VOCAB).replace("677 - row_number() OVER (ORDER BY rank)", "count(*) OVER () + 1 - row_number() OVER (ORDER BY rank)")


def own_letters(s: SparkSession, d: str) -> str:
    """The letters of the documents' words, in order."""
    return "".join(sorted(r["c"] for r in words(s, d).select(F.explode(F.array_distinct(F.split("word", ""))).alias("c")).distinct().collect()))


@query(sql(OWN_VOCAB, "SELECT surface, has_space::INT AS spaced, n_letters FROM staged"))
def staged_vocab(s, d):
    return tokenize.staged_vocab(s, own_letters(s, d)).select("surface", F.col("has_space").cast("int").alias("spaced"), "n_letters")


@query(sql(OWN_MERGES, 'SELECT rank::INT AS rank, stage, l AS "left", r AS "right", merged FROM merges'))
def staged_merges(s, d):
    return tokenize.staged_merges(s, SEED, own_letters(s, d))


@query(sql(OWN_MERGES, 'SELECT l AS "left", r AS "right", strength::BIGINT AS strength FROM strength'))
def merge_strength(s, d):
    return stats.merge_strength(tokenize.staged_merges(s, SEED, own_letters(s, d))).select("left", "right", F.col("strength").cast("long").alias("strength"))


@query(sql(CHUNKS + ", " + BOUNDARY, "SELECT * FROM boundary"))
def boundary_pairs(s, d):
    return stats.fixed_boundary_pairs(words(s, d))


@query(sql(CHUNKS + ", " + BOUNDARY, "SELECT * FROM boundary"))
def boundary_pairs_of_tokens(s, d):
    return stats.boundary_pairs(chunks(s, d))


@query(sql(CHUNKS + ", " + BOUNDARY, "SELECT * FROM inside"))
def inner_pairs(s, d):
    return stats.inner_pairs(chunks(s, d))


@query(sql(CHUNKS + ", " + BOUNDARY, "SELECT last, first, coalesce(b.freq, 0)::BIGINT AS at_boundary, coalesce(i.freq, 0)::BIGINT AS inside, round(coalesce(b.freq, 0) / (coalesce(b.freq, 0) + coalesce(i.freq, 0)), 9) AS rate FROM boundary b FULL JOIN inside i USING (last, first)"))
def boundary_rate(s, d):
    return stats.boundary_rate(stats.fixed_boundary_pairs(words(s, d)), stats.inner_pairs(chunks(s, d)))


RANKED = "met AS (SELECT strength, coalesce(freq, 0) AS freq FROM strength LEFT JOIN boundary ON l = last AND r = first), ranked AS (SELECT rank() OVER (ORDER BY strength) + (count(*) OVER (PARTITION BY strength) - 1) / 2 AS a, rank() OVER (ORDER BY freq) + (count(*) OVER (PARTITION BY freq) - 1) / 2 AS b FROM met)"


@query(sql(CHUNKS + ", " + BOUNDARY + ", " + MERGES + ", " + RANKED, "SELECT count(*) AS pairs, round(corr(a, b), 9) AS spearman FROM ranked"))
def strength_vs_boundary(s, d):
    return stats.strength_vs_boundary(stats.merge_strength(tokenize.staged_merges(s, SEED)), stats.fixed_boundary_pairs(words(s, d)))


@query(sql(CHUNKS + ", " + BOUNDARY + ", t AS (SELECT last, first, freq, sum(freq) OVER () AS n, sum(freq) OVER (PARTITION BY last) AS a, sum(freq) OVER (PARTITION BY first) AS b FROM boundary)", "SELECT sum(freq)::BIGINT AS n, round(sum(freq / n * log2(freq * n / (a * b))), 9) AS bits, round((count(DISTINCT last) - 1) * (count(DISTINCT first) - 1) / (2 * sum(freq) * ln(2)), 9) AS bias FROM t"))
def boundary_mi(s, d):
    return stats.boundary_mi(stats.fixed_boundary_pairs(words(s, d)))


@query(sql(WORDS + """, p AS (SELECT unnest(['ck', 'dge', 'tch', 'bb', 'dd', 'ff', 'll', 'nn', 'ss', 'tt']) AS pattern), m AS (SELECT word, freq, pattern, position(pattern IN word) AS spot FROM counts, p WHERE contains(word, pattern)),
r AS (SELECT pattern, CASE WHEN spot = 1 THEN 'start' WHEN spot + length(pattern) - 1 = length(word) THEN 'end' ELSE 'middle' END AS place, CASE WHEN spot > 1 AND substr(word, spot - 1, 1) IN ('a', 'e', 'i', 'o', 'u') THEN 'vowel' ELSE 'other' END AS before, freq FROM m)""", "SELECT pattern, place, before, sum(freq)::BIGINT AS weight FROM r GROUP BY CUBE (pattern, place, before)"))
def pattern_position_cube(s, d):
    return stats.pattern_position(corpus.word_counts(words(s, d)))


@query(sql(WORDS + ", a AS (SELECT unnest(['s', 'ed', 'er', 'ly', 'ful', 'tion']) AS affix), h AS (SELECT affix, freq, CASE WHEN ends_with(word, affix) AND length(word) > length(affix) + 1 THEN freq ELSE 0 END AS hit FROM counts, a)", "SELECT affix, sum(hit)::BIGINT AS weight, round(sum(hit) / sum(freq), 9) AS share FROM h GROUP BY affix"))
def affix_share(s, d):
    return stats.affix_share(corpus.word_counts(words(s, d)))


@query(sql(CHUNKS + ", " + BOUNDARY + ", " + MERGES + ", met AS (SELECT strength, ln(1 + coalesce(freq, 0)) AS f FROM strength LEFT JOIN boundary ON l = last AND r = first)", "SELECT count(*) AS pairs, round(corr(strength, f), 9) AS pearson FROM met"))
def strength_vs_log_boundary(s, d):
    return stats.pearson_of_logs(stats.merge_strength(tokenize.staged_merges(s, SEED)), stats.fixed_boundary_pairs(words(s, d)))


@query(sql(CHUNKS + ", " + BOUNDARY + ", " + MERGES + ", met AS (SELECT strength, coalesce(freq, 0) AS freq FROM strength LEFT JOIN boundary ON l = last AND r = first), b AS (SELECT *, ntile(10) OVER (ORDER BY strength DESC) AS bin FROM met)", "SELECT bin::INT AS bin, sum(freq)::BIGINT AS boundary_freq, count(*) AS pairs FROM b GROUP BY 1"))
def strength_bins(s, d):
    return stats.binned(stats.merge_strength(tokenize.staged_merges(s, SEED)), stats.fixed_boundary_pairs(words(s, d)))


@query(sql(WORDS, "SELECT count(*) AS types, round(corr(length(word), ln(f)), 9) AS pearson FROM (SELECT word, sum(freq) AS f FROM counts GROUP BY word)"))
def length_frequency_corr(s, d):
    return stats.length_frequency_corr(corpus.word_counts(words(s, d)))


@query(sql(CHUNKS + ", " + BOUNDARY + ", a AS (SELECT last, sum(freq) AS a FROM boundary GROUP BY last), b AS (SELECT first, sum(freq) AS b FROM boundary GROUP BY first), p AS (SELECT last, first, round(a * b / (SELECT sum(freq) FROM boundary))::BIGINT AS freq FROM a, b), q AS (SELECT * FROM p WHERE freq > 0), t AS (SELECT last, first, freq, sum(freq) OVER () AS n, sum(freq) OVER (PARTITION BY last) AS a, sum(freq) OVER (PARTITION BY first) AS b FROM q)", "SELECT sum(freq)::BIGINT AS n, round(sum(freq / n * log2(freq * n / (a * b))), 9) AS bits, round((count(DISTINCT last) - 1) * (count(DISTINCT first) - 1) / (2 * sum(freq) * ln(2)), 9) AS bias FROM t"))
def boundary_mi_shuffled(s, d):
    return stats.shuffled_mi(stats.fixed_boundary_pairs(words(s, d)))


# -- interventions -----------------------------------------------------------------------------------------------


@query(f"""WITH b AS (SELECT item_id, text, string_split(text, '') AS c FROM benchmark)
SELECT item_id, array_to_string(list_transform(c, lambda x, i: CASE WHEN x BETWEEN 'a' AND 'z' AND ascii(x) < 128 THEN chr((97 + ('0x' || substr(md5(concat_ws('|', '{SEED}', item_id, i - 1)), 1, 8))::BIGINT % 26)::INT) WHEN x BETWEEN 'A' AND 'Z' AND ascii(x) < 128 THEN chr((65 + ('0x' || substr(md5(concat_ws('|', '{SEED}', item_id, i - 1)), 1, 8))::BIGINT % 26)::INT) ELSE x END), '') AS scrambled FROM b""")
def scramble_letters(s, d):
    return table(s, d, "benchmark").select("item_id", rewrite.scramble_letters(F.col("text"), SEED, F.col("item_id")).alias("scrambled"))


SHORT = f"""one AS (SELECT chr(97 + i::INT) AS c FROM range(26) t(i)), strings AS (SELECT c AS x FROM one UNION ALL SELECT a.c || b.c FROM one a, one b),
src AS (SELECT x, row_number() OVER (PARTITION BY length(x) ORDER BY md5({key_sql("'src'", 'x')}), x) AS k FROM strings), dst AS (SELECT x, row_number() OVER (PARTITION BY length(x) ORDER BY md5({key_sql("'dst'", 'x')}), x) AS k FROM strings)"""


@query(sql(CHUNKS + ", " + SHORT, "SELECT src.x AS src, dst.x AS dst, length(src.x)::INT AS n_letters FROM src JOIN dst ON src.k = dst.k AND length(src.x) = length(dst.x) WHERE src.x IN (SELECT surface FROM tokens)"))
def substitution_dict_short(s, d):
    return rewrite.substitution_short(chunks(s, d), SEED).select("src", "dst", F.col("n_letters").cast("int").alias("n_letters"))


@query()
def substitute_words(s, d):
    w = words(s, d)
    return rewrite.substitute_words(w, rewrite.substitution_all(w.select(F.col("word").alias("surface")), SEED))


@query(sql(CHUNKS + f""", entries AS (SELECT DISTINCT surface AS s2, has_space AS g, n_letters AS n FROM tokens), numbered AS (SELECT s2, g, n, row_number() OVER (PARTITION BY g, n ORDER BY s2) - 1 AS k, count(*) OVER (PARTITION BY g, n) AS size FROM entries),
sizes AS (SELECT DISTINCT g, n, size FROM numbered), drawn AS (SELECT t.*, {draw_sql('doc_id', 'word_pos', 'sub_pos')} % size AS k FROM tokens t JOIN sizes ON g = has_space AND n = n_letters)""", "SELECT doc_id, word_pos::INT AS word_pos, sub_pos::INT AS sub_pos, s2 AS surface FROM drawn JOIN numbered ON numbered.g = has_space AND numbered.n = n_letters AND numbered.k = drawn.k"))
def resample_tokens(s, d):
    t = chunks(s, d)
    return rewrite.resample_tokens(t, t.select("surface", "has_space", "n_letters").distinct(), SEED).select("doc_id", "word_pos", "sub_pos", "surface")


@query(sql(WORDS, "SELECT doc_id, string_agg((CASE WHEN has_space THEN ' ' ELSE '' END) || word, '' ORDER BY pos) AS text FROM words GROUP BY doc_id"))
def reassemble(s, d):
    return rewrite.reassemble(words(s, d))


@query()
def lemmatize(s, d):
    return rewrite.lemmatize(corpus.word_counts(words(s, d)))


@query()
def stem(s, d):
    return rewrite.stem(corpus.word_counts(words(s, d)))


@query(sql(WORDS, "SELECT DISTINCT word, CASE WHEN length(word) <= 2 THEN word WHEN ends_with(word, 'sses') OR ends_with(word, 'ies') THEN left(word, length(word) - 2) WHEN ends_with(word, 'ss') THEN word WHEN ends_with(word, 's') THEN left(word, length(word) - 1) ELSE word END AS stem FROM words"))
def stem_step1a(s, d):
    return words(s, d).select("word").distinct().select("word", rewrite.stem_step1a(F.col("word")).alias("stem"))


@query(sql(CHUNKS, f"SELECT doc_id, count(*) AS tokens, sum(({draw_sql('doc_id', 'word_pos', 'sub_pos')} % 10000 < 1500)::INT)::BIGINT AS masked FROM tokens GROUP BY doc_id"))
def mask_draw(s, d):
    return encode.mask_draw(chunks(s, d), 0.15, SEED).groupBy("doc_id").agg(F.count("*").alias("tokens"), F.sum("masked").alias("masked"))


# -- vectors -----------------------------------------------------------------------------------------------------

SEQUENCE = VOCAB + """, seq AS MATERIALIZED (SELECT doc_id, token_id, row_number() OVER (PARTITION BY doc_id ORDER BY pos) AS i FROM words JOIN vocab ON word = surface AND words.has_space = vocab.has_space)"""
FORWARD = SEQUENCE + ", cooc AS MATERIALIZED (SELECT a.token_id AS t, b.token_id AS c, count(*) AS n FROM seq a JOIN seq b ON a.doc_id = b.doc_id AND b.i BETWEEN a.i + 1 AND a.i + 2 GROUP BY ALL)"


def word_sequences(s, d):
    t = words(s, d).select("doc_id", F.col("pos").alias("word_pos"), F.lit(0).alias("sub_pos"), F.col("word").alias("surface"), "has_space")
    return encode.sequences(t, word_vocab(s, d))


@query(sql(FORWARD, "SELECT t, c, n FROM cooc"))
def cooc_forward(s, d):
    return encode.cooccurrence(word_sequences(s, d), 2, "forward").select(F.col("t").cast("long").alias("t"), F.col("c").cast("long").alias("c"), "n")


@query(sql(FORWARD, "SELECT t, c, sum(n)::BIGINT AS n FROM (SELECT t, c, n FROM cooc UNION ALL SELECT c, t, n FROM cooc) GROUP BY ALL"))
def cooc_symmetric(s, d):
    return encode.cooccurrence(word_sequences(s, d), 2, "both").select(F.col("t").cast("long").alias("t"), F.col("c").cast("long").alias("c"), "n")


@query(sql(FORWARD + ", nt AS (SELECT t, sum(n) AS n_t FROM cooc GROUP BY t), wc AS (SELECT c, pow(sum(n), 0.75) AS w FROM cooc GROUP BY c), v AS (SELECT t, c, round(round(ln(n * (SELECT sum(w) FROM wc) / (n_t * w)), 9), 6) AS value FROM cooc JOIN nt USING (t) JOIN wc USING (c))", "SELECT t, c, value FROM v WHERE value > 0"))
def ppmi(s, d):
    m = encode.ppmi(encode.cooccurrence(word_sequences(s, d), 2, "forward"))
    return m.select(F.col("t").cast("long").alias("t"), F.col("c").cast("long").alias("c"), F.round("value", 6).alias("value")).where("value > 0")


# -- trained tokenizers ------------------------------------------------------------------------------------------


def spelled_counts(s, d):
    c = corpus.word_counts(words(s, d))
    return c.select(F.split(F.concat(F.when(F.col("has_space"), " ").otherwise(""), "word"), "").alias("symbols"), "freq")


PAIRS = WORDS + """, spelled0 AS (SELECT string_split((CASE WHEN has_space THEN ' ' ELSE '' END) || word, '') AS symbols, freq FROM counts)"""


def _round_sql(k: int) -> str:
    return f""", idx{k} AS (SELECT symbols, freq, unnest(range(1, len(symbols))) AS i FROM spelled{k}), pairs{k} AS MATERIALIZED (SELECT symbols[i] AS l, symbols[i + 1] AS r, sum(freq) AS n FROM idx{k} GROUP BY ALL)"""


@query(sql(PAIRS + _round_sql(0), 'SELECT l AS "left", r AS "right", n::BIGINT AS n FROM pairs0'))
def bpe_pairs_round1(s, d):
    return tokenize.pair_counts(spelled_counts(s, d))


@query()
def bpe_pairs_round2(s, d):
    rules = tokenize.bpe_train_distributed(spelled_counts(s, d), 2)
    return s.createDataFrame([(k, a, b, n) for k, (a, b, n) in enumerate(rules)], "rank int, left string, right string, n long")


@query()
def bpe_train(s, d):
    return tokenize.bpe_merges(words(s, d), 500)


@query()
def bpe_encode(s, d):
    w = words(s, d)
    return tokenize.bpe_encode(w, tokenize.bpe_merges(w, 300))


@query()
def staged_encode(s, d):
    return tokenize.exploded(experiments.staged_rows(s, d)[0].select("doc_id", "pos", "pieces"))


@query()
def merge_trace(s, d):
    """How the fifty most frequent words merge, step by step."""
    w = words(s, d)
    s.udtf.register("merge_trace", tokenize.trace_function(tokenize._ordered_rules(tokenize.bpe_merges(w, 300))))
    corpus.word_counts(w).orderBy(F.desc("freq"), "word", "has_space").limit(50).createOrReplaceTempView("traced_words")
    return s.sql("SELECT word, has_space, t.step, t.rank, array_join(t.symbols, '|') AS symbols FROM traced_words, LATERAL merge_trace(word, has_space) t")


@query()
def wordpiece_train(s, d):
    pieces = tokenize.wordpiece_vocab(words(s, d), 300)
    return s.createDataFrame([(k, x) for k, x in enumerate(pieces)], "token_id int, piece string")


@query()
def wordpiece_encode(s, d):
    w = words(s, d)
    return tokenize.exploded(tokenize.wordpiece_encode(w, tokenize.wordpiece_vocab(w, 300)))


@query()
def unigram_train(s, d):
    logp, _ = tokenize.unigram_model(words(s, d), 300, 1, 0.5)
    return s.createDataFrame(sorted((x, float(p)) for x, p in logp.items()), "piece string, log_probability double")


@query()
def unigram_encode(s, d):
    w = words(s, d)
    return tokenize.exploded(tokenize.unigram_encode(w, tokenize.unigram_model(w, 300, 1, 0.5)[0]))


@query()
def unigram_sample(s, d):
    w = words(s, d)
    return tokenize.exploded(tokenize.unigram_encode(w, tokenize.unigram_model(w, 300, 1, 0.5)[0], 0.3, SEED))


@query()
def scramble_documents(s, d):
    return rewrite.scrambled_documents(english(s, d), SEED)


@query()
def substitute_subwords(s, d):
    w = words(s, d)
    coded = experiments.coded_words(w)
    return rewrite.substitute_subwords(w, rewrite.subword_substitution(coded, SEED), coded)


@query()
def pack_blocks(s, d):
    return encode.pack_blocks(word_sequences(s, d).repartition(8, "doc_id").sortWithinPartitions("doc_id"), 256).select(F.array_join("ids", " ").alias("ids"))


@query(sql(WORDS + """, chars AS (SELECT word, unnest(string_split(word, '')) AS c, generate_subscripts(string_split(word, ''), 1) AS i, f FROM (SELECT word, sum(freq) AS f FROM counts GROUP BY word)),
units AS (SELECT (CASE WHEN i > 1 THEN '##' ELSE '' END) || c AS u, sum(f) AS n FROM chars GROUP BY 1), near AS (SELECT (CASE WHEN i > 1 THEN '##' ELSE '' END) || c AS l, '##' || lead(c) OVER (PARTITION BY word ORDER BY i) AS r, f FROM chars),
p AS (SELECT l, r, sum(f) AS n FROM near WHERE r IS NOT NULL GROUP BY ALL)""", 'SELECT l AS "left", r AS "right", p.n::BIGINT AS n, round(p.n / (a.n::DOUBLE * b.n), 15) AS score FROM p JOIN units a ON a.u = l JOIN units b ON b.u = r'))
def wordpiece_scores_round1(s, d):
    c = corpus.word_counts(words(s, d)).groupBy("word").agg(F.sum("freq").alias("freq"))
    marked = F.transform(F.split("word", ""), lambda x, i: F.when(i > 0, F.concat(F.lit("##"), x)).otherwise(x))
    c = c.select(marked.alias("symbols"), "freq")
    units = c.select(F.explode("symbols").alias("u"), "freq").groupBy("u").agg(F.sum("freq").alias("total"))
    p = tokenize.pair_counts(c).join(units.select(F.col("u").alias("left"), F.col("total").alias("a")), "left").join(units.select(F.col("u").alias("right"), F.col("total").alias("b")), "right")
    return p.select("left", "right", "n", F.round(F.col("n") / (F.col("a").cast("double") * F.col("b")), 15).alias("score"))


# -- events ------------------------------------------------------------------------------------------------------


@query("SELECT epoch_us(date_trunc('hour', ts)) AS start_us, event_type, count(*) AS n, round(sum(value), 6) AS total FROM events GROUP BY ALL")
def events_tumbling(s, d):
    return streaming.event_windows(table(s, d, "events")).select(F.unix_micros("start").alias("start_us"), "event_type", "n", "total")


@query("WITH w AS (SELECT event_type, value, date_trunc('hour', ts) - INTERVAL (k * 30) MINUTE + INTERVAL (CASE WHEN minute(ts) >= 30 THEN 30 ELSE 0 END) MINUTE AS start FROM events, range(2) t(k)) SELECT epoch_us(start) AS start_us, event_type, count(*) AS n, round(sum(value), 6) AS total FROM w GROUP BY ALL")
def events_sliding(s, d):
    return streaming.event_windows(table(s, d, "events"), "1 hour", "30 minutes").select(F.unix_micros("start").alias("start_us"), "event_type", "n", "total")


@query("WITH o AS (SELECT user_id, ts, (ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts)) > INTERVAL 30 MINUTE AS gap FROM events), g AS (SELECT user_id, ts, sum(coalesce(gap, true)::INT) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM o) SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM g GROUP BY user_id, k")
def events_session(s, d):
    return streaming.event_sessions(table(s, d, "events")).select("user_id", F.unix_micros("start").alias("start_us"), "n")


@query("WITH c AS (SELECT event_id, ts FROM events WHERE event_type = (SELECT min(event_type) FROM events)) SELECT e.event_id, (SELECT c.event_id FROM c WHERE c.ts <= e.ts ORDER BY c.ts DESC, c.event_id DESC LIMIT 1) AS checkpoint_id FROM events e WHERE e.ts >= (SELECT min(ts) FROM c)")
def asof_checkpoint(s, d):
    e = table(s, d, "events")
    kind = e.agg(F.min("event_type").alias("kind"))
    # All rows in one order: the marked row last seen. Days are numbered apart, so that no task holds the whole stream.
    marked = e.crossJoin(F.broadcast(kind)).select("event_id", "ts", F.to_date("ts").alias("day"), F.when(F.col("event_type") == F.col("kind"), F.struct("ts", "event_id")).alias("mark"))
    in_day = Window.partitionBy("day").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    days = marked.groupBy("day").agg(F.max("mark").alias("last_of_day"))
    before = Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)  # a row a day
    carried = days.select("day", F.max("last_of_day").over(before).alias("carried"))
    return marked.withColumn("own", F.max("mark").over(in_day)).join(F.broadcast(carried), "day", "left").select("event_id", F.coalesce("own.event_id", "carried.event_id").alias("checkpoint_id")).where("checkpoint_id is not null")


# -- experiments -------------------------------------------------------------------------------------------------

for _f in experiments.ALL:
    _spark[_f.__name__] = _f
