"""Text workloads: the pattern ladder, every predicate of the index, measures, matrices, tree operators."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from treeloom.baselines import engines as B
from treeloom.engine.columnar import Columnar, count_nodes
from treeloom.engine.planner import cut_off, text_path
from treeloom.sources.store import built_once
from treeloom.sources.trees import open_tree, table
from treeloom.text import measures, pssm, qgram, shards
from treeloom.text.plain import occurrences, text_condition
from treeloom.text.rank import rank_frame
from treeloom.tree import nav, paren
from treeloom.workloads.paths import ABS, WORDS
from treeloom.workloads.registry import register

LADDER = ["license", "@", "thshst", "erüver", "Nicht", "License", "para", "the of", "The", "\n", "ing", "the", "a", "b", "g", "Copyright"]


def texts_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("text_id"), F.col("text").alias("value"))


def shards_of(spark: SparkSession, sf_dir: str, sample: int = 64, kind: str = "blocks") -> DataFrame:
    return built_once(spark, sf_dir, f"shards-{sample}-{kind}", lambda: shards.build_shards(texts_of(spark, sf_dir), sample, kind, 1 << 20, 8), wide=True)


def _quoted(p: str) -> str:
    return "chr(10)" if p == "\n" else "'" + p.replace("'", "''") + "'"


def _per_pattern(expr: str, patterns: list[str] = LADDER, source: str = "documents") -> str:
    return " UNION ALL ".join(f"SELECT {_quoted(p)} AS pattern, {expr.replace('?', _quoted(p))} FROM {source}" for p in patterns)


#: No pattern of the ladder overlaps itself, so replacing counts them all.
_OCC = "coalesce(sum((length(text) - length(replace(text, ?, ''))) // length(?)), 0)::BIGINT AS occurrences"
_TXT = "count_if(contains(text, ?))::BIGINT AS texts"


@register("ladder_global_count", _per_pattern(_OCC))
def ladder_global(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shards.global_count(shards_of(spark, sf_dir), LADDER)


for _l in (64, 4):

    @register(f"ladder_contains_count_{_l}", _per_pattern(f"{_OCC}, {_TXT}"))
    def ladder_contains(spark: SparkSession, sf_dir: str, sample: int = _l) -> DataFrame:
        return shards.counts(shards_of(spark, sf_dir, sample), LADDER)


_RARE = ["license", "thshst", "erüver", "Nicht", "License", "para"]


def _report_sql(test: str, patterns: list[str], column: str = "doc_id") -> str:
    return " UNION ALL ".join(f"SELECT {_quoted(p)} AS pattern, {column} AS text_id FROM documents WHERE {test.replace('?', _quoted(p))}" for p in patterns)


@register("ladder_contains_report", _report_sql("contains(text, ?)", LADDER))
def ladder_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shards.search(shards_of(spark, sf_dir), "contains", LADDER)


for _kind in ("wavelet", "huffman", "runs"):

    @register(f"index_kind_{_kind}", _per_pattern(f"{_OCC}, {_TXT}", _RARE))
    def index_kind(spark: SparkSession, sf_dir: str, kind: str = _kind) -> DataFrame:
        return shards.counts(shards_of(spark, sf_dir, 16, kind), _RARE)


_PREDICATES = {
    "starts_with": ("starts-with", "starts_with(text, ?)", ["The", "Le", "Und"]),
    "ends_with": ("ends-with", "suffix(text, ?)", [".", "License", "the."]),
    "less": ("<", "text < ?", ["B", "The"]),
    "at_most": ("<=", "text <= ?", ["B", "The"]),
    "greater": (">", "text > ?", ["The", "Und"]),
    "at_least": (">=", "text >= ?", ["The", "Und"]),
}
for _name, (_op, _test, _patterns) in _PREDICATES.items():

    @register(f"index_{_name}", _report_sql(_test, _patterns))
    def predicate(spark: SparkSession, sf_dir: str, op: str = _op, patterns: tuple = tuple(_patterns)) -> DataFrame:
        return shards.search(shards_of(spark, sf_dir), op, list(patterns))

    @register(f"plain_{_name}", _report_sql(_test, _patterns))
    def plain(spark: SparkSession, sf_dir: str, op: str = _op, patterns: tuple = tuple(_patterns)) -> DataFrame:
        texts = texts_of(spark, sf_dir)
        return reduce(DataFrame.unionAll, [texts.filter(text_condition(op, F.col("value"), p)).select(F.lit(p).alias("pattern"), "text_id") for p in patterns])


#: The first text in order: a pattern that some texts are equal to.
_EQUAL = "SELECT md5(text) AS pattern, doc_id AS text_id FROM documents WHERE text = (SELECT min(text) FROM documents WHERE text <> '')"


def _first_text(texts: DataFrame) -> str:
    return texts.filter("value <> ''").agg(F.min("value")).first()[0] or " "


@register("index_equals", _EQUAL)
def index_equals(spark: SparkSession, sf_dir: str) -> DataFrame:
    word = _first_text(texts_of(spark, sf_dir))
    return shards.search(shards_of(spark, sf_dir), "=", [word]).select(F.md5("pattern").alias("pattern"), "text_id")


@register("plain_equals", _EQUAL)
def plain_equals(spark: SparkSession, sf_dir: str) -> DataFrame:
    texts = texts_of(spark, sf_dir)
    word = _first_text(texts)
    return texts.filter(text_condition("=", F.col("value"), word)).select(F.md5("value").alias("pattern"), "text_id")


@register("index_id_range", _report_sql("contains(text, ?) AND doc_id BETWEEN 100 AND 400", ["License", "para"]))
def id_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shards.search(shards_of(spark, sf_dir), "contains", ["License", "para"], (100, 400))


@register("index_locate", "SELECT doc_id AS text_id, (strlen(string_split(text, 'erüver')[1]))::BIGINT AS \"offset\" FROM documents WHERE contains(text, 'erüver')")
def locate_first(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First occurrence in each text, in bytes."""
    return shards.locate(shards_of(spark, sf_dir, 4), "erüver").groupBy("text_id").agg(F.min("offset").alias("offset"))


@register("index_extract", "SELECT doc_id AS text_id, md5(text) AS digest FROM documents")
def extract_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every whole text read back from the index of all documents, compared by digest."""
    return shards.extract(shards_of(spark, sf_dir)).select("text_id", F.md5("value").alias("digest"))


@register("index_merge", _per_pattern(f"{_OCC}, {_TXT}", _RARE))
def merged_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shards.counts(shards.compact(shards_of(spark, sf_dir)), _RARE)


def _one_off(word: str) -> str:
    """Expression for an ASCII word with one byte changed; at its ends that byte may belong to a longer character."""
    return "|".join(word[:i] + ("." if i in (0, len(word) - 1) else r"[\x01-\x7F]") + word[i + 1 :] for i in range(len(word)))


@register("index_approximate", f"SELECT 'thxngand' AS pattern, item_id AS text_id FROM benchmark WHERE regexp_matches(text, '(?s){_one_off('thxngand')}') UNION ALL SELECT 'thxng', item_id FROM benchmark WHERE regexp_matches(text, '(?s){_one_off('thxng')}')")
def approximate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shards.search(shards.build_shards(_small(spark, sf_dir), 64, "blocks", 1 << 20, 2), "approximate", ["thxng", "thxngand"], errors=1)


def _one_edit(word: str) -> str:
    """Expression for an ASCII word with one character changed, missing or more."""
    missing = [word[:i] + word[i + 1 :] for i in range(len(word))]
    more = [word[:i] + "." + word[i:] for i in range(1, len(word))]
    return "|".join(dict.fromkeys([_one_off(word), *missing, *more, word]))


@register("index_edit_distance", " UNION ALL ".join(f"SELECT '{w}' AS pattern, item_id AS text_id FROM benchmark WHERE regexp_matches(text, '(?s){_one_edit(w)}')" for w in ("thinng", "ereheon")))
def edit_distance(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shards.search(shards.build_shards(_small(spark, sf_dir), 64, "blocks", 1 << 20, 2), "edits", ["thinng", "ereheon"], errors=1)


_EXPRESSIONS = ["[A-Z][a-z]+ License", "(th)+shst", "(x|y)[0-9]"]


@register("regex_contains", " UNION ALL ".join(f"SELECT '{e}' AS expression, doc_id AS text_id FROM documents WHERE regexp_matches(text, '{e}')" for e in _EXPRESSIONS))
def regex_contains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Texts that hold what each expression requires, by their q-grams, then the expression; a scan where it requires too little."""
    texts, frames = texts_of(spark, sf_dir), []
    for e in _EXPRESSIONS:
        needed = qgram.required_text(e)
        some = texts.join(qgram.candidates(_postings(spark, sf_dir), needed), "text_id", "left_semi") if len(needed) >= qgram.Q else texts
        frames.append(some.filter(F.col("value").rlike(e)).select(F.lit(e).alias("expression"), "text_id"))
    return reduce(DataFrame.unionAll, frames)


def _postings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return built_once(spark, sf_dir, "postings", lambda: qgram.build_postings(texts_of(spark, sf_dir)), ["gram", "text_id"])


@register("qgram_contains", " UNION ALL ".join(f"SELECT '{p}' AS pattern, doc_id AS text_id FROM documents WHERE contains(text, '{p}')" for p in ("License", "thshst", "the of")))
def qgram_contains(spark: SparkSession, sf_dir: str) -> DataFrame:
    post, texts = _postings(spark, sf_dir), texts_of(spark, sf_dir)
    return reduce(DataFrame.unionAll, [qgram.contains(post, texts, p).select(F.lit(p).alias("pattern"), "text_id") for p in ("License", "thshst", "the of")])


_OCC_OF = f"o AS ({_per_pattern(_OCC)}), b AS (SELECT sum(strlen(text))::BIGINT AS b FROM documents), c AS (SELECT pattern, sample::INTEGER AS sample, occurrences, greatest(1, CASE WHEN sample > 4 THEN b * 4 // (sample * 125) ELSE b // 150 END)::BIGINT AS cut_off FROM o, b, (SELECT unnest([64, 4]) AS sample))"


@register("text_path_choice", f"WITH {_OCC_OF} SELECT *, CASE WHEN occurrences < cut_off THEN 'index' ELSE 'scan' END AS choice FROM c")
def text_path_choice(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Index or scan for each pattern of the ladder, at both sampling steps."""
    n = texts_of(spark, sf_dir).agg(F.sum(F.octet_length("value"))).first()[0] or 0
    rows = shards.global_count(shards_of(spark, sf_dir), LADDER).collect()
    out = [(r["pattern"], l, r["occurrences"], cut_off(n, l), text_path(r["occurrences"], n, l)) for r in rows for l in (64, 4)]
    return spark.createDataFrame(out, "pattern string, sample int, occurrences long, cut_off long, choice string")


@register("overlapping_count", "SELECT 'aa' AS pattern, coalesce(sum(len(list_filter(range(1, length(text)), lambda i: substr(text, i, 2) = 'aa'))), 0)::BIGINT AS occurrences FROM benchmark")
def overlapping(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "benchmark").agg(F.coalesce(F.sum(occurrences(F.col("text"), "aa")), F.lit(0)).alias("occurrences")).select(F.lit("aa").alias("pattern"), "occurrences")


@register("baseline_plain_scan", _per_pattern(f"{_OCC}, {_TXT}"))
def plain_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    texts = texts_of(spark, sf_dir)
    return reduce(DataFrame.unionAll, [B.plain_scan(texts, p).select(F.lit(p).alias("pattern"), "occurrences", "texts") for p in LADDER])


def _words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return built_once(spark, sf_dir, "words", lambda: B.build_words(texts_of(spark, sf_dir)), ["word", "text_id"])


@register("baseline_word_index", _report_sql("contains(text, ?)", ["License", "the of", "ing"]))
def word_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    words, texts = _words(spark, sf_dir), texts_of(spark, sf_dir)
    return reduce(DataFrame.unionAll, [B.word_contains(words, texts, p).select(F.lit(p).alias("pattern"), "text_id") for p in ("License", "the of", "ing")])


_HAS = lambda w: f"list_contains(string_split_regex(text, '[\\x20\\x09-\\x0D]+'), '{w}')"


@register("baseline_word_boolean", f"SELECT doc_id AS text_id FROM documents WHERE {_HAS('the')} AND {_HAS('of')} AND NOT {_HAS('Nicht')} AND ({_HAS('License')} OR {_HAS('is')})")
def word_boolean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return B.word_boolean(_words(spark, sf_dir), ["the", "of"], ["Nicht"], ["License", "is"])


@register("baseline_word_regex", r"SELECT doc_id AS text_id FROM documents WHERE len(list_filter(string_split_regex(text, '[\x20\x09-\x0D]+'), lambda w: regexp_matches(w, '^Lic[a-z]+e[.,]?$'))) > 0")
def word_regex(spark: SparkSession, sf_dir: str) -> DataFrame:
    return B.word_regex(_words(spark, sf_dir), "^Lic[a-z]+e[.,]?$")


@register(
    "baseline_ranked",
    r"""WITH w AS (SELECT doc_id, unnest(regexp_split_to_array(text, '[\x20\x09-\x0D]+')) AS word FROM documents),
t AS (SELECT word, doc_id, count(*) AS n FROM w WHERE word IN ('License', 'thshst', 'Nicht') GROUP BY 1, 2),
i AS (SELECT word, ln((SELECT count(*) FROM documents)::DOUBLE / count(*)) AS idf FROM t GROUP BY 1)
SELECT doc_id AS text_id, round(sum(n * idf), 6) AS score FROM t JOIN i USING (word) GROUP BY 1 ORDER BY score DESC, text_id LIMIT 10""",
)
def ranked(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = texts_of(spark, sf_dir).count()
    return B.ranked(_words(spark, sf_dir), n, ["License", "thshst", "Nicht"], 10)


# --- measures ---------------------------------------------------------------------------------------------------------


def _small(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("text_id"), F.col("text").alias("value"))


_CHARS = "c AS (SELECT item_id, unnest(range(1, length(text) + 1)) AS i, unnest(regexp_extract_all(text, '(?s).')) AS c FROM benchmark)"
for _k in (0, 1, 2):
    _ctx = "''" if not _k else " || ".join(f"lag(c, {j}) OVER w" for j in range(_k, 0, -1))

    @register(
        f"entropy_h{_k}",
        f"WITH {_CHARS}, x AS (SELECT i, c, {_ctx} AS ctx FROM c WINDOW w AS (PARTITION BY item_id ORDER BY i)), p AS (SELECT ctx, c, count(*) AS n FROM x WHERE i > {_k} GROUP BY 1, 2), m AS (SELECT *, sum(n) OVER (PARTITION BY ctx) AS m FROM p) SELECT round(sum(-n * log2(n / m)) / sum(n), 6) AS h FROM m",
    )
    def entropy(spark: SparkSession, sf_dir: str, k: int = _k) -> DataFrame:
        return measures.entropy(_small(spark, sf_dir), k)


@register("symbol_starts", f"WITH {_CHARS}, n AS (SELECT c, count(*) AS n FROM c GROUP BY 1) SELECT c, n, (sum(n) OVER (ORDER BY c) - n)::BIGINT AS smaller FROM n")
def symbol_starts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.symbol_starts(_small(spark, sf_dir))


@register("rank_select", f"WITH {_CHARS} SELECT item_id AS text_id, i, c, row_number() OVER (PARTITION BY item_id, c ORDER BY i)::BIGINT AS rank FROM c")
def rank_select(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rank_frame(measures.characters(_small(spark, sf_dir)).withColumn("i", F.col("i").cast("long")), ["text_id"], "i", "c")


@register("bwt_rotations", "WITH r AS (SELECT item_id, i, substr(text || chr(1), i) || substr(text || chr(1), 1, i - 1) AS rot FROM (SELECT item_id, text, unnest(range(1, length(text) + 2)) AS i FROM benchmark)) SELECT item_id AS text_id, string_agg(right(rot, 1), '' ORDER BY rot) AS bwt FROM r GROUP BY 1")
def bwt_rotations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The transform of every small text, in characters, from its rotations."""
    t = _small(spark, sf_dir).withColumn("s", F.concat("value", F.lit("\x01")))
    rots = F.transform(F.sequence(F.lit(1), F.length("s")), lambda i: F.concat(F.substr("s", i, F.length("s")), F.substr("s", F.lit(1), i - 1)))
    return t.select("text_id", F.array_join(F.transform(F.array_sort(rots), lambda r: F.right(r, F.lit(1))), "").alias("bwt"))


@register("store_offsets", "SELECT doc_id AS text_id, (sum(strlen(text) + 1) OVER (ORDER BY doc_id) - strlen(text) - 1)::BIGINT AS start FROM documents")
def store_offsets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.store_offsets(texts_of(spark, sf_dir), 256)


@register("measure_index_sizes")
def index_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return reduce(DataFrame.unionAll, [shards.sizes(shards_of(spark, sf_dir, s, k)) for s, k in ((64, "blocks"), (4, "blocks"), (16, "huffman"), (16, "wavelet"), (16, "runs"))])


@register("measure_occurrence_ratio", _per_pattern(f"round(({_OCC.split(' AS')[0]}) / greatest(1, count_if(contains(text, ?))), 4) AS ratio"))
def occurrence_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shards.counts(shards_of(spark, sf_dir), LADDER).select("pattern", F.round(F.col("occurrences") / F.greatest("texts", F.lit(1)), 4).alias("ratio"))


@register("measure_recursive_labels", "SELECT 'thread' AS label, count(DISTINCT conv_id)::BIGINT AS n, 0::BIGINT AS n_recursive FROM conversations UNION ALL SELECT 'turn', count(*)::BIGINT, count_if(turn > 0)::BIGINT FROM conversations")
def recursive_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nav.recursive_counts(open_tree(spark, sf_dir, "threads").nodes)


# --- tree operators on conversations: a document is &, thread, @, id, %, then turns ---------------------------------------

#: pre of turn t: 6 + 5 t (its text, @, role, % follow in front of the next turn)
_T = "SELECT conv_id AS doc, turn, row_number() OVER (PARTITION BY conv_id ORDER BY turn) - 1 AS t, count(*) OVER (PARTITION BY conv_id) AS m FROM conversations"


def _threads(spark: SparkSession, sf_dir: str) -> DataFrame:
    return open_tree(spark, sf_dir, "threads").nodes


@register("tree_turn_intervals", f"WITH t AS ({_T}) SELECT doc, (6 + 5 * t)::BIGINT AS pre, (5 + 5 * m)::BIGINT AS last, (3 + t)::INTEGER AS depth FROM t")
def turn_intervals(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _threads(spark, sf_dir).filter("label = 'turn' and kind = 'elem'").select("doc", "pre", "last", "depth")


@register("tree_close_positions", f"WITH t AS ({_T}) SELECT doc, (2 * (6 + 5 * t) - (3 + t))::BIGINT AS open, (2 * (6 + 5 * t) - (3 + t) + 2 * (5 * (m - t)) - 1)::BIGINT AS \"close\", (5 * (m - t))::BIGINT AS size FROM t")
def close_positions(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = _threads(spark, sf_dir).filter("label = 'turn' and kind = 'elem'")
    return turns.select("doc", nav.open_position().alias("open"), nav.close_position().alias("close"), nav.subtree_size().alias("size"))


@register("tree_subtree_tags", f"WITH t AS ({_T}) SELECT doc, (6 + 5 * t)::BIGINT AS pre, (m - t)::BIGINT AS n_label FROM t")
def subtree_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nav.subtree_tags(_threads(spark, sf_dir), "turn").filter("label = 'turn' and kind = 'elem'").select("doc", "pre", "n_label")


@register("tree_tagged_desc", f"WITH t AS ({_T}) SELECT doc, (6 + 5 * t)::BIGINT AS pre, CASE WHEN t + 1 < m THEN 11 + 5 * t ELSE 0 END::BIGINT AS tagged_desc FROM t")
def tagged_desc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nav.tagged_desc(_threads(spark, sf_dir), "turn").filter("label = 'turn' and kind = 'elem'").select("doc", "pre", F.coalesce("tagged_desc", F.lit(0)).alias("tagged_desc"))


_ART = f"WITH {ABS}, n AS (SELECT doc_id, count(*) AS m FROM abs GROUP BY 1)"
#: A citation: & citation @ id % lang % art, then abs and its text, from 9 on; empty attribute values have no leaf.


@register("tree_tagged_foll", f"{_ART} SELECT abs.doc_id AS doc, (7 + 2 * k)::BIGINT AS pre, CASE WHEN k < m THEN 9 + 2 * k ELSE 0 END::BIGINT AS tagged_foll FROM abs JOIN n USING (doc_id)")
def tagged_foll(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nav.tagged_foll(open_tree(spark, sf_dir, "citations").nodes, "abs").filter("label = 'abs'").select("doc", "pre", F.coalesce("tagged_foll", F.lit(0)).alias("tagged_foll"))


@register("tree_tagged_prec", f"{_ART} SELECT abs.doc_id AS doc, (7 + 2 * k)::BIGINT AS pre, CASE WHEN k > 1 THEN 5 + 2 * k ELSE 0 END::BIGINT AS tagged_prec FROM abs JOIN n USING (doc_id)")
def tagged_prec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nav.tagged_prec(open_tree(spark, sf_dir, "citations").nodes, "abs").filter("label = 'abs'").select("doc", "pre", F.coalesce("tagged_prec", F.lit(0)).alias("tagged_prec"))


@register("tree_siblings", f"{_ART} SELECT abs.doc_id AS doc, (7 + 2 * k)::BIGINT AS pre, (8 + 2 * k)::BIGINT AS first_child, (9 + 2 * k)::BIGINT AS next_sibling FROM abs JOIN n USING (doc_id)")
def siblings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nav.siblings(open_tree(spark, sf_dir, "citations").nodes).filter("label = 'abs'").select("doc", "pre", "first_child", "next_sibling")


@register("tree_text_ranges", f"{_ART} SELECT abs.doc_id AS doc, (7 + 2 * k)::BIGINT AS pre, k::BIGINT AS first_text, k::BIGINT AS last_text FROM abs")
def text_ranges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nav.text_ranges(open_tree(spark, sf_dir, "citations").nodes).filter("label = 'abs'").select("doc", "pre", "first_text", "last_text")


@register("tree_node_of_text", f"WITH {ABS} SELECT doc_id AS doc, 10::BIGINT AS pre FROM abs WHERE k = 1")
def node_of_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    nodes = open_tree(spark, sf_dir, "citations").nodes
    ids = nodes.filter("label = 'abs' and ord = 1").select("doc", F.lit(1).cast("long").alias("text_no"))
    return nav.node_of_text(nodes, ids).select("doc", "pre")


@register("tree_ith_child", f"WITH {ABS} SELECT doc_id AS doc, (7 + 2 * k)::BIGINT AS pre FROM abs WHERE k = 2")
def ith_child(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nav.child(open_tree(spark, sf_dir, "citations").nodes, 2).filter("label = 'abs'").select("doc", "pre")


@register("tree_is_ancestor", f"WITH t AS ({_T}) SELECT doc, sum(m - t)::BIGINT AS n FROM t GROUP BY 1")
def is_ancestor(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = _threads(spark, sf_dir).filter("label = 'turn' and kind = 'elem'")
    return turns.alias("x").join(turns.alias("y"), nav.is_ancestor("x", "y")).groupBy(F.col("x.doc").alias("doc")).agg(F.count("*").alias("n"))


@register("tree_topmost", "SELECT DISTINCT conv_id AS doc, 6::BIGINT AS pre FROM conversations")
def topmost(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nav.topmost(_threads(spark, sf_dir), "turn").select("doc", "pre")


@register("tree_bottom_most", "SELECT conv_id AS doc, (1 + 5 * count(*))::BIGINT AS pre FROM conversations GROUP BY 1")
def bottom_most(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nav.bottom_most(_threads(spark, sf_dir), "turn").select("doc", "pre")


@register("tree_parentheses_round_trip", f"WITH t AS ({_T}) SELECT doc, (6 + 5 * t)::BIGINT AS pre, (5 + 5 * m)::BIGINT AS last, (3 + t)::INTEGER AS depth FROM t")
def parentheses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Columns to parentheses and back; the turns of the result."""
    nodes = _threads(spark, sf_dir)
    back = paren.from_sequence(paren.sequence(nodes))
    turns = nodes.filter("label = 'turn' and kind = 'elem'").select("doc", "pre")
    return back.join(turns, ["doc", "pre"], "left_semi").select("doc", "pre", "last", "depth")


@register(
    "tree_tag_sequence",
    "SELECT conv_id AS doc, '<& <thread <@ <id <% /% /id /@ ' || repeat('<turn <@ <role <% /% /role /@ <# /# ', count(*)::INT) || repeat('/turn ', count(*)::INT) || '/thread /&' AS tags FROM conversations GROUP BY 1",
)
def tag_sequence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The label sequence of each document: two symbols a node."""
    return paren.tag_sequence(_threads(spark, sf_dir))


@register("entropy_tag_sequence", "WITH n AS (SELECT unnest(['&', 'thread', '@', 'id', '%', 'turn', 'role', '#']) AS label, unnest([d, d, d + t, d, d + t, t, t, t]) AS n FROM (SELECT count(DISTINCT conv_id) AS d, count(*) AS t FROM conversations)) SELECT round(sum(-n * log2(n / (SELECT sum(n) FROM n))) / sum(n), 6) AS h FROM n")
def entropy_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits a label of the label sequence: what a compressed sequence is measured against."""
    counts = _threads(spark, sf_dir).groupBy("label").agg(F.count("*").alias("n"))
    whole = counts.agg(F.sum("n").alias("m"))
    return counts.crossJoin(F.broadcast(whole)).agg(F.round(F.sum(-F.col("n") * F.log2(F.col("n") / F.col("m"))) / F.sum("n"), 6).alias("h"))


# --- matrices ---------------------------------------------------------------------------------------------------------

_BASES = "regexp_replace(translate(regexp_replace(lower(text), '[^a-z]', '', 'g'), 'abcdefghijklmnopqrstuvwxyz', 'ACGTACGTACGTACGTACGTACGTAC'), '[^ACGT]', '', 'g')"


def _matrix_rows(name: str) -> str:
    w = pssm.log_odds(pssm.FREQUENCIES[name])
    return ", ".join(f"({k}, '{c}', {x})" for k, col in enumerate(w) for c, x in col.items())


def _matrix_sql(values: str, name: str, out: str) -> str:
    length = len(pssm.FREQUENCIES[name])
    return f"""WITH m(k, c, w) AS (VALUES {_matrix_rows(name)}), v AS ({values}),
p AS (SELECT id, s, unnest(range(1, length(s) - {length - 2})) AS i FROM v WHERE length(s) >= {length}),
x AS (SELECT id, i, sum(w) AS score FROM p JOIN m ON substr(s, i + k, 1) = c GROUP BY 1, 2)
SELECT {out} FROM (SELECT DISTINCT id FROM x WHERE score > {pssm.THRESHOLDS[name]})"""


def _elements_sql(name: str) -> str:
    """Sequences of genes, of transcripts (every other line) and of their sentences, with the first 1000 bases as promoters."""
    bases = lambda x: _BASES.replace("lower(text)", f"lower({x})")
    values = f"""SELECT row_number() OVER () AS id, kind, s FROM (
  SELECT 'gene' AS kind, {bases('text')} AS s FROM documents WHERE lang = 'en'
  UNION ALL SELECT 'promoter', substr({bases('text')}, 1, 1000) FROM documents WHERE lang = 'en'
  UNION ALL SELECT 'line', {bases('line')} FROM l WHERE k % 2 = 0
  UNION ALL SELECT 'exon', {bases('x')} FROM (SELECT unnest(string_split(line, '.')) AS x FROM l WHERE k % 2 = 0))"""
    lines = "l AS (SELECT unnest(range(len(string_split(text, chr(10))))) AS k, unnest(string_split(text, chr(10))) AS line FROM documents WHERE lang = 'en'), u AS MATERIALIZED (" + values + ")"
    hit = _matrix_sql("SELECT id, s FROM u", name, "id").replace("WITH m(", f"WITH {lines}, m(", 1)
    return f"SELECT 'exon' AS query, count(*)::BIGINT AS n FROM ({hit.replace('SELECT id FROM (SELECT DISTINCT id FROM x', 'SELECT id FROM u WHERE kind = $$exon$$ AND id IN (SELECT id FROM x')}) UNION ALL SELECT 'any', count(*)::BIGINT FROM ({hit})"


for _m in pssm.FREQUENCIES:
    _promoters = f"SELECT doc_id AS id, substr({_BASES}, 1, 1000) AS s FROM documents WHERE lang = 'en'"

    @register(f"matrix_promoter_{_m.lower()}", _matrix_sql(_promoters, _m, "id AS doc"))
    def promoter(spark: SparkSession, sf_dir: str, m: str = _m) -> DataFrame:
        tree = open_tree(spark, sf_dir, "genes")
        owner = Columnar(tree).select("//promoter").select("doc", F.col("pre").alias("parent"))
        texts = tree.texts.filter("kind = 'text'").join(owner, ["doc", "parent"], "left_semi").select("doc", "value")
        return pssm.matches(texts, pssm.log_odds(pssm.FREQUENCIES[m]), pssm.THRESHOLDS[m]).select("doc")

    @register(f"matrix_index_promoter_{_m.lower()}", _matrix_sql(_promoters, _m, "id AS doc"))
    def promoter_index(spark: SparkSession, sf_dir: str, m: str = _m) -> DataFrame:
        """The same through an index of the promoters, by backtracking."""
        tree = open_tree(spark, sf_dir, "genes")
        owner = Columnar(tree).select("//promoter").select("doc", F.col("pre").alias("parent"))
        texts = lambda: built_once(spark, sf_dir, "promoter-texts", lambda: tree.texts.filter("kind = 'text'").join(owner, ["doc", "parent"], "left_semi").select(F.col("doc").alias("text_id"), "value"))
        index = built_once(spark, sf_dir, "promoter-shards", lambda: shards.build_shards(texts(), 16, "blocks", 1 << 20, 4), wide=True)
        return shards.matrix(index, pssm.log_odds(pssm.FREQUENCIES[m]), pssm.THRESHOLDS[m]).select(F.col("text_id").alias("doc"))

    @register(f"matrix_elements_{_m.lower()}", _elements_sql(_m))
    def matrix_elements(spark: SparkSession, sf_dir: str, m: str = _m) -> DataFrame:
        """Exons with a matching sequence, and elements of any label that hold a matching text, as paths."""
        col = Columnar(open_tree(spark, sf_dir, "genes"))
        paths = {"exon": f'//exon[sequence[matrix(., "{m}")]]', "any": f'//*[matrix(., "{m}")]'}
        return reduce(DataFrame.unionAll, [count_nodes(col.select(p)).select(F.lit(q).alias("query"), "n") for q, p in paths.items()])


@register("runs_of_transform", "WITH r AS (SELECT item_id, i, substr(text || chr(1), i) || substr(text || chr(1), 1, i - 1) AS rot FROM (SELECT item_id, text, unnest(range(1, length(text) + 2)) AS i FROM benchmark)), l AS (SELECT item_id, right(rot, 1) AS c, lag(right(rot, 1)) OVER (PARTITION BY item_id ORDER BY rot) AS p FROM r) SELECT item_id AS text_id, count_if(p IS NULL OR p <> c)::BIGINT AS n_runs FROM l GROUP BY 1")
def runs_of_transform(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Runs of the transform: what the repetition-aware index stores."""
    t = bwt_rotations(spark, sf_dir).select("text_id", F.posexplode(F.filter(F.split("bwt", ""), lambda c: c != "")).alias("i", "c"))
    before = F.lag("c").over(Window.partitionBy("text_id").orderBy("i"))
    return t.withColumn("p", before).groupBy("text_id").agg(F.count_if(F.col("p").isNull() | (F.col("p") != F.col("c"))).alias("n_runs"))


@register("hybrid_terms_by_label", f"WITH {WORDS} SELECT l.quality, count(*)::BIGINT AS n FROM words JOIN labels l USING (doc_id) WHERE length(w) >= 12 GROUP BY 1")
def terms_by_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hits of a path joined back to a relational table."""
    tree = open_tree(spark, sf_dir, "market")
    col = Columnar(tree)
    terms = col.select("//entry//term")
    owner = tree.texts.filter("kind = 'attr' and label = 'id'").select("frag", F.col("value").cast("long").alias("doc_id"))
    return terms.join(owner, "frag").join(table(spark, sf_dir, "labels"), "doc_id").groupBy("quality").agg(F.count("*").alias("n"))
