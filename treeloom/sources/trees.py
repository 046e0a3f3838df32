"""The stand-in trees over the given tables, as ``nodes`` and ``texts`` tables.

``nodes``: doc, frag, pre, last, depth, parent, ord, label, kind (doc, elem, attrs, attr, text, value), host, value.
``frag`` tells the fragments of a large document apart; nodes above all fragments (the spine) have frag -1, and every
fragment's interval lies inside one.  Attribute nodes carry the value of their leaf.
"""

from __future__ import annotations

import json
import re
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from treeloom.sources.html import parse_html
from treeloom.sources.store import built_once
from treeloom.tree.encode import ROOT, Node, encode_records, number_records, outline_records

COLUMNS = ["doc", "frag", "pre", "last", "depth", "parent", "ord", "label", "kind", "host", "value"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def leaf(label: str, text: object) -> Node:
    return Node(label, [] if text is None else [str(text)])


def whole_documents(df: DataFrame) -> DataFrame:
    """Documents that are one record each: one fragment, no spine."""
    return df.withColumn("frag", F.lit(0)).select(*COLUMNS)


# --- market: one document, products, members and deals under a spine -----------------------------------------------


def _entry(line: str, nested: Node | None) -> Node:
    out = Node("entry", [line] if line else [])
    words = line.split(" ")
    out.children += [Node("term", [w, Node("strong", [w])] if len(w) >= 16 else [w]) for w in words if len(w) >= 12]
    out.children += [Node("heavy", [w]) for w in words if len(w) >= 8 and w.endswith(".")]
    if nested is not None:
        out.children.append(Node("list", [nested]))
    return out


def _product(key: int, name: str, brand: str, text: str | None) -> Node:
    out = Node("product", [leaf("name", name), leaf("brand", brand)], {"id": str(key)})
    if text is not None:
        entries: list[Node] = []
        lines = text.split("\n")
        k = 0
        while k < len(lines):
            nests = k + 1 < len(lines) and (k + 1) % 3 == 2
            entries.append(_entry(lines[k], _entry(lines[k + 1], None) if nests else None))
            k += 2 if nests else 1
        out.children.append(Node("body", [Node("list", entries)]))
    return out


def _member(key: int, name: str, nation: int, nation_name: str, balance: float, open_orders: bool) -> Node:
    out = Node("member", [leaf("label", name)], {"id": str(key)})
    if nation < 20:
        out.children.append(leaf("residence", nation_name))
    if key % 2 == 0:
        out.children.append(leaf("tel", f"+{key}"))
    if key % 3 == 0:
        out.children.append(leaf("site", f"site{key}"))
    if balance > 5000:
        out.children.append(leaf("card", f"card{key}"))
    if key % 4:
        persona = Node("persona")
        if key % 5:
            persona.children.append(leaf("sex", "female" if key % 2 else "male"))
        if key % 7:
            persona.children.append(leaf("years", 18 + key % 60))
        out.children.append(persona)
    if open_orders:
        out.children.append(Node("follows"))
    return out


def _deal(key: int, day: str, cost: str, terms: list | None) -> Node:
    out = Node("deal", [leaf("day", day), leaf("cost", cost)], {"id": str(key)})
    if terms is not None:
        para = Node("para", [Node("term", [t["name"], *([Node("strong", [t["name"]])] if t["discount"] >= 0.05 else [])]) for t in sorted(terms, key=lambda t: t["line"])])
        out.children.append(Node("note", [Node("body", [para])]))
    return out


def _market_records(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[str]]:
    """Outlines of all records with section and order, and the labels of the zones."""
    t = lambda name: table(spark, sf_dir, name)
    zones = [r[0].lower().replace(" ", "_") for r in t("region").orderBy("r_regionkey").select("r_name").collect()]
    part = t("part").select("p_partkey", "p_name", "p_brand")
    bodies = t("documents").select(F.col("doc_id").alias("p_partkey"), "text")
    products = part.join(bodies, "p_partkey", "left").withColumn("section", F.concat(F.lit("zone"), (F.col("p_partkey") % len(zones)).cast("string"))).withColumn("o", F.col("p_partkey"))
    nation = t("nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_name")
    open_orders = t("orders").filter("o_orderstatus = 'O'").select(F.col("o_custkey").alias("c_custkey")).distinct().withColumn("follows", F.lit(True))
    members = (
        t("customer").join(F.broadcast(nation), "c_nationkey", "left").join(open_orders, "c_custkey", "left")
        .withColumn("follows", F.coalesce("follows", F.lit(False))).withColumn("section", F.lit("members")).withColumn("o", F.col("c_custkey"))
    )
    lines = t("lineitem").filter("l_returnflag = 'R'").select("l_orderkey", "l_linenumber", "l_discount", F.col("l_partkey").alias("p_partkey")).join(part.select("p_partkey", "p_name"), "p_partkey")
    terms = lines.groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.collect_list(F.struct(F.col("l_linenumber").alias("line"), F.col("p_name").alias("name"), F.col("l_discount").alias("discount"))).alias("terms"))
    orders = t("orders").select("o_orderkey", "o_orderstatus", F.date_format("o_orderdate", "yyyy-MM-dd").alias("day"), F.format_string("%.2f", "o_totalprice").alias("cost"))
    settled = orders.filter("o_orderstatus = 'F'").join(terms, "o_orderkey", "left").withColumn("terms", F.coalesce("terms", F.array().cast(terms.schema["terms"].dataType)))
    running = orders.filter("o_orderstatus <> 'F'").withColumn("terms", F.lit(None).cast(terms.schema["terms"].dataType))
    deals = settled.withColumn("section", F.lit("settled")).unionByName(running.withColumn("section", F.lit("running"))).withColumn("o", F.col("o_orderkey"))
    out = lambda df, make, cols: outline_records(df, make, cols, "section", "o")
    records = out(products, _product, ["p_partkey", "p_name", "p_brand", "text"])
    records = records.unionByName(out(members, _member, ["c_custkey", "c_name", "c_nationkey", "n_name", "c_acctbal", "follows"]))
    return records.unionByName(out(deals, _deal, ["o_orderkey", "day", "cost", "terms"])), zones


def build_market(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Records come in order, range by range, so that the place of one is that of its range and what lies before it there: no node is
    dealt out, and nodes are made when their numbers are known."""
    local, zones = _market_records(spark, sf_dir)
    local = built_once(spark, sf_dir, "market-local", lambda: local, narrow=True)
    ranges = local.groupBy("section", "part").agg(F.min("o").alias("o"), F.sum("size").alias("n")).orderBy("section", "o").collect()  # as many as tasks
    total: dict[str, int] = {}
    before: list[tuple[str, int, int]] = []
    for r in ranges:
        before.append((r["section"], r["part"], total.get(r["section"], 0)))
        total[r["section"]] = before[-1][2] + r["n"]
    # the spine, with the room that each section's records take
    spine: list[tuple] = []
    starts: dict[str, tuple[int, int, int]] = {}

    def put(label: str, depth: int, parent: int, order: int, kind: str = "elem") -> int:
        spine.append([len(spine) + 1 + sum(total.get(s, 0) for s in starts), 0, depth, parent, order, label, kind])
        return spine[-1][0]

    def close(row: list) -> None:
        row[1] = len(spine) + sum(total.get(s, 0) for s in starts)

    def room(section: str, parent: int) -> None:
        starts[section] = (len(spine) + sum(total.get(s, 0) for s in starts), parent, spine[-1][2] + 1)

    root = put(ROOT, 1, 0, 1, "doc")
    market = put("market", 2, root, 1)
    top = [spine[0], spine[1]]
    z = put("zones", 3, market, 1)
    zrow = spine[-1]
    for i, label in enumerate(zones):
        me = put(label, 4, z, i + 1)
        row = spine[-1]
        room(f"zone{i}", me)
        close(row)
    close(zrow)
    for k, section in enumerate(("members", "settled", "running"), 2):
        me = put(section, 3, market, k)
        row = spine[-1]
        room(section, me)
        close(row)
    for row in top:
        close(row)
    where = spark.createDataFrame([(s, k, n + starts[s][0], *starts[s][1:]) for s, k, n in before], "section string, part int, base long, up long, depth int")
    frag = F.xxhash64("section", "o")
    placed = local.join(F.broadcast(where), ["section", "part"]).select(
        F.lit(0).cast("long").alias("doc"), F.when(frag == -1, 0).otherwise(frag).alias("frag"), (F.col("base") + F.col("at")).alias("shift"), "up", "depth", "size", "shape", "lengths", "texts"
    )
    records = number_records(placed, ["doc", "frag"]).select(*COLUMNS)
    head = spark.createDataFrame([(0, -1, *r, None, None) for r in spine], "doc long, frag long, pre long, last long, depth int, parent long, ord int, label string, kind string, host long, value string")
    return head.unionByName(records)


# --- citations, threads, pages, genes, events: one document a row --------------------------------------------------


def _citation(doc: int, text: str | None, lang: str | None, quality: int | None, nation: str | None) -> Node:
    lines = [x for x in (text or "").split("\n") if x]
    art = Node("art", [leaf("abs", x) for x in lines])
    art.children.append(Node("writers", [Node("writer", [leaf("surname", x.split(" ")[0])]) for x in lines]))
    art.children += [leaf("yr", 1992 + doc % 7), leaf("kind", {1: "Journal Article", 0: "Letter"}.get(quality, "Note")), leaf("nation", nation)]
    return Node(ROOT, [Node("citation", [art], {"id": str(doc), "lang": lang or ""})])


def build_citations(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang").join(table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id", "left")
    nation = table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("k"), "n_name")
    docs = docs.join(F.broadcast(nation), docs["doc_id"] % 25 == nation["k"], "left").withColumnRenamed("doc_id", "doc")
    return whole_documents(encode_records(docs, _citation, ["doc", "text", "lang", "quality", "n_name"], ["doc"]))


def _thread(conv: int, turns: list) -> Node:
    below: Node | None = None
    for t in sorted(turns, key=lambda t: -t["turn"]):
        below = Node("turn", [*([t["text"]] if t["text"] else []), *([below] if below else [])], {"role": t["role"] or ""})
    return Node(ROOT, [Node("thread", [below] if below else [], {"id": str(conv)})])


def build_threads(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations").groupBy(F.col("conv_id").alias("doc")).agg(F.collect_list(F.struct("turn", "role", "text")).alias("turns"))
    return whole_documents(encode_records(turns, _thread, ["doc", "turns"], ["doc"]))


def build_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select(F.col("page_id").alias("doc"), "html")
    return whole_documents(encode_records(pages, parse_html, ["html"], ["doc"]))


_TO_BASE = {ord(c): "ACGT"[i % 4] for i, c in enumerate("abcdefghijklmnopqrstuvwxyz")}
_NO_BASE = re.compile("[^ACGT]+")


def to_bases(text: str) -> str:
    return _NO_BASE.sub("", text.lower().translate(_TO_BASE))


def _gene(doc: int, text: str | None) -> Node:
    lines = (text or "").split("\n")
    whole = to_bases(text or "")
    gene = Node("gene", [leaf("name", f"gene{doc}"), leaf("strand", "+" if doc % 2 else "-"), leaf("promoter", whole[:1000]), leaf("sequence", whole)], {"id": str(doc)})
    at = 0
    for i, line in enumerate(lines):
        n = len(to_bases(line))
        if i % 2 == 0:
            exons, begin = [], at
            for j, sentence in enumerate(x for x in line.split(".") if to_bases(x)):
                s = to_bases(sentence)
                exons.append(Node("exon", [leaf("name", f"exon{j}"), leaf("start", begin), leaf("end", begin + len(s)), leaf("sequence", s)]))
                begin += len(s)
            gene.children.append(Node("transcript", [leaf("name", f"transcript{i}"), leaf("start", at), leaf("end", at + n), *exons, leaf("sequence", to_bases(line))]))
        at += n
    return Node(ROOT, [gene])


def build_genes(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").filter("lang = 'en'").select(F.col("doc_id").alias("doc"), "text")
    return whole_documents(encode_records(docs, _gene, ["doc", "text"], ["doc"]))


def _event(kind: str | None, user: int | None, value: float | None, props: str | None) -> Node:
    try:
        inner = json.loads(props or "{}")
    except ValueError:
        inner = {}
    return Node(ROOT, [Node("event", [leaf("value", value), Node("props", [leaf(k, v) for k, v in inner.items()])], {"type": kind or "", "user": str(user)})])


def event_nodes(events: DataFrame) -> DataFrame:
    """The small document of each event; works on a stream as on a table."""
    return whole_documents(encode_records(events.withColumnRenamed("event_id", "doc"), _event, ["event_type", "user_id", "value", "props"], ["doc"]))


def build_eventlog(spark: SparkSession, sf_dir: str) -> DataFrame:
    return event_nodes(table(spark, sf_dir, "events"))


BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "market": build_market, "citations": build_citations, "threads": build_threads, "pages": build_pages, "genes": build_genes, "eventlog": build_eventlog,
}


_spined: dict[tuple, bool] = {}
#: (occurrences, text bytes, sampling step) of words that were asked for, by built tree.
_counted: dict[tuple, tuple[int, int, int]] = {}


class Tree:
    """A built tree: its ``nodes``, the ``texts`` among them, and per-label counts."""

    def __init__(self, spark: SparkSession, nodes: DataFrame, name: str = "", source: str = "", use_index: bool = False):
        self.spark, self.all, self.name, self.source, self.use_index = spark, nodes, name, source, use_index
        #: without values: what plans that test no text read
        self.nodes = nodes.drop("value")
        self._stats: dict[str, tuple[int, int]] | None = None

    @property
    def spined(self) -> bool:
        """Whether some document is cut into fragments below a spine; asked once a built tree."""
        key = (self.spark.sparkContext.applicationId, self.source, self.name or id(self))
        if key not in _spined:
            _spined[key] = not self.nodes.filter("frag = -1").isEmpty()
        return _spined[key]

    @property
    def index(self) -> DataFrame | None:
        """The text index, built at first use; None for a tree that is not kept under a name."""
        if not self.name or not self.use_index:
            return None
        from treeloom.engine.textindex import build_tree_index

        def build() -> DataFrame:
            spine = [tuple(r) for r in self.nodes.filter("frag = -1").select("doc", "pre", "last", "label").collect()] if self.spined else []
            return build_tree_index(self.all, spine)

        return built_once(self.spark, self.source, f"{self.name}-index", build, wide=True)

    def pairs(self) -> set[tuple[str, str, str]]:
        """The (axis, a, b) of element labels that occur, kept beside a tree that is kept under a name; labels squared bounds them."""
        from treeloom.tree.labelpairs import build_pairs

        kept = built_once(self.spark, self.source, f"{self.name}-pairs", lambda: build_pairs(self.nodes)) if self.name else build_pairs(self.nodes)
        return {tuple(r) for r in kept.select("axis", "a", "b").collect()}

    def occurrences(self, kind: str, word: str) -> tuple[int, int, int] | None:
        """(occurrences, bytes of all texts, sampling step) by backward search; None if the index cannot tell."""
        from treeloom.engine.textindex import count_hits, indexable

        if self.index is None or not indexable(kind, word):
            return None
        key = (self.spark.sparkContext.applicationId, self.source, self.name, kind, word)
        if key not in _counted:
            _counted[key] = count_hits(self.index, kind, word)
        return _counted[key]

    def by_index(self, kind: str, word: str) -> bool:
        """Whether the index answers a text predicate sooner than a scan of all texts."""
        from treeloom.text.cutoff import text_path

        got = self.occurrences(kind, word)
        return got is not None and text_path(*got) == "index"

    def matching(self, kind: str, word: str) -> DataFrame:
        """doc, frag, pre, parent, label, kind, host of the texts and attribute values that satisfy a predicate: from the index,
        or by a scan where the word is too frequent for it."""
        from treeloom.engine.textindex import search_texts
        from treeloom.text.plain import text_condition

        if self.by_index(kind, word):
            return search_texts(self.index, kind, word)
        return self.texts.filter(text_condition(kind, F.col("value"), word)).select("doc", "frag", "pre", "parent", "label", "kind", "host")

    @property
    def texts(self) -> DataFrame:
        """Text and attribute values with the element that has them."""
        return self.all.filter(F.col("kind").isin("text", "attr")).select("doc", "frag", "pre", "parent", "depth", "label", "kind", "host", "value")

    def stats(self) -> dict[str, tuple[int, int]]:
        """Nodes and summed depth of every element and attribute label; one small aggregate."""
        if self._stats is None:
            rows = self.nodes.filter(F.col("kind").isin("elem", "attr")).groupBy("kind", "label").agg(F.count("*").alias("n"), F.sum("depth").alias("d")).collect()
            self._stats = {("@" if r["kind"] == "attr" else "") + r["label"]: (r["n"], r["d"]) for r in rows}
        return self._stats


#: Bytes of outlined records that a task makes nodes of; they take up ten times that.
RECORDS_SPLIT = 4 << 20
#: Trees whose texts are indexed unless the caller says otherwise.
TEXT_INDEXED = ("citations",)


def open_tree(spark: SparkSession, sf_dir: str, name: str, use_index: bool | None = None) -> Tree:
    """A stand-in tree; ``use_index``: text predicates go through its text index where that is sooner."""
    nodes = built_once(spark, sf_dir, name, lambda: BUILDERS[name](spark, sf_dir), ["label", "doc", "pre"], split=RECORDS_SPLIT if name == "market" else None)
    return Tree(spark, nodes, name, sf_dir, name in TEXT_INDEXED if use_index is None else use_index)


def value_of(kind: Column, value: Column) -> Column:
    return F.when(kind.isin("text", "attr", "value"), value)
