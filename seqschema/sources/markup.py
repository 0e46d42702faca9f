"""Child strings of markup elements: one string for each occurrence of an element, in document order."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from html.parser import HTMLParser
from xml.parsers import expat

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Elements without content, and elements whose start ends an open one of the listed kinds.
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"}
BLOCKS = ("p", "div", "ul", "ol", "table", "h1", "h2", "h3", "h4", "h5", "h6", "pre", "form", "section", "article", "footer", "header", "nav", "blockquote")
ENDS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}} | dict.fromkeys(BLOCKS, {"p"})
#: What an implied end may not reach beyond.
FENCES = {"html", "body", "div", "article", "section", "ul", "ol", "table", "td", "th", "nav", "footer", "header", "blockquote"}


class Elements(HTMLParser):
    def __init__(self, implied_end: bool) -> None:
        super().__init__(convert_charrefs=True)
        self.implied_end, self.open, self.found = implied_end, [], []

    def handle_starttag(self, tag, attrs) -> None:
        if self.implied_end and tag in ENDS:
            for k in range(len(self.open) - 1, -1, -1):
                if self.open[k][0] in ENDS[tag]:
                    del self.open[k:]
                    break
                if self.open[k][0] in FENCES:
                    break
        if self.open:
            self.open[-1][1].append(tag)
        element = (tag, [], self.open[-1][0] if self.open else "")
        self.found.append(element)
        if tag not in VOID:
            self.open.append(element)

    def handle_startendtag(self, tag, attrs) -> None:
        self.handle_starttag(tag, attrs)
        if tag not in VOID:
            self.open.pop()

    def handle_endtag(self, tag) -> None:
        for k in range(len(self.open) - 1, -1, -1):
            if self.open[k][0] == tag:
                del self.open[k:]
                break


def html_elements(text: str, implied_end: bool = True) -> list[tuple[str, list[str], str]]:
    parser = Elements(implied_end)
    parser.feed(text)
    parser.close()
    return parser.found


def xml_elements(text: str) -> list[tuple[str, list[str], str]]:
    """Of a well-formed document; of a broken one, nothing."""
    found: list = []
    open_: list = []

    def start(tag, attrs):
        if open_:
            open_[-1][1].append(tag)
        open_.append((tag, [], open_[-1][0] if open_ else ""))
        found.append(open_[-1])

    parser = expat.ParserCreate()
    parser.StartElementHandler, parser.EndElementHandler = start, lambda tag: open_.pop()
    try:
        parser.Parse(text, True)
    except expat.ExpatError:
        return []
    return found


def strings_from_markup(docs: DataFrame, col: str, mode: str = "xml", implied_end: bool = True, context: int = 0) -> DataFrame:
    """(model_key, string_id, seq): model_key is the element's name, after its parent's with context=1."""

    @F.pandas_udf("array<struct<tag:string,parent:string,seq:array<string>>>")
    def elements(texts: pd.Series) -> pd.Series:
        read = xml_elements if mode == "xml" else lambda t: html_elements(t, implied_end)
        return pd.Series([[{"tag": t, "parent": p, "seq": s} for t, s, p in read(x or "")] for x in texts])

    rows = docs.select(F.xxhash64(col).alias("_d"), F.posexplode(elements(F.col(col))).alias("_n", "e"))
    key = F.concat_ws("/", "e.parent", "e.tag") if context else F.col("e.tag")
    return rows.select(key.alias("model_key"), F.concat_ws(":", "_d", "_n").alias("string_id"), F.col("e.seq").alias("seq"))


#: Symbols of different strings that a worker holds before it hands their numbers on; a string counts as one more.
HELD = 500_000


def distinct_from_markup(docs: DataFrame, col: str, mode: str = "xml", implied_end: bool = True, context: int = 0, most: int = HELD) -> DataFrame:
    """(model_key, seq, n): distinct_strings() of strings_from_markup(). Documents are read one by one and workers count
    equal strings, so neither memory nor the shuffle grows with the elements of a batch."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, held = Counter(), 0

        def rows() -> pa.RecordBatch:
            keys, seqs = zip(*found, strict=True)
            return pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array(seqs, pa.list_(pa.string())), pa.array(found.values(), pa.int64())], names=["model_key", "seq", "n"])

        for b in batches:
            for text in b.column(0):
                text = text.as_py() or ""
                for tag, seq, parent in xml_elements(text) if mode == "xml" else html_elements(text, implied_end):
                    one = (f"{parent}/{tag}" if context else tag), tuple(seq)
                    found[one] += 1
                    if found[one] == 1:
                        held += 1 + len(seq)
                if held > most:
                    yield rows()
                    found, held = Counter(), 0
        if found:
            yield rows()

    counted = docs.select(F.col(col)).mapInArrow(work, "model_key string, seq array<string>, n bigint")
    return counted.groupBy("model_key", "seq").agg(F.sum("n").alias("n"))


def published_xml(spark, sf_dir: str) -> DataFrame:
    """(key, xml): the star schema as documents of bounded size, null fields left out. A region holds its nations; a
    customer its orders, those their line items, and these their part and supplier. Customers name their nation by key:
    inside it, one document would hold a share of all rows that grows with them."""
    from seqschema.sources.tables import table

    below = lambda key, *fields: F.when(F.col(key).isNotNull(), F.struct(key, *fields))
    parts, suppliers = table(spark, sf_dir, "part").select("p_partkey", "p_brand"), table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    lines = table(spark, sf_dir, "lineitem").join(parts, F.col("l_partkey") == F.col("p_partkey"), "left").join(suppliers, F.col("l_suppkey") == F.col("s_suppkey"), "left")
    line = F.struct("l_linenumber", "l_quantity", "l_returnflag", below("p_partkey", "p_brand").alias("part"), below("s_suppkey", "s_nationkey").alias("supplier"))
    lines = lines.groupBy("l_orderkey").agg(F.array_sort(F.collect_list(line)).alias("lineitem"))
    orders = table(spark, sf_dir, "orders").join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    orders = orders.select("o_custkey", F.struct("o_orderkey", "o_orderstatus", "o_orderpriority", "lineitem").alias("order")).groupBy("o_custkey").agg(F.array_sort(F.collect_list("order")).alias("order"))
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey").join(orders, F.col("c_custkey") == F.col("o_custkey"), "left")
    nations = table(spark, sf_dir, "nation").groupBy("n_regionkey").agg(F.array_sort(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("nation"))
    regions = table(spark, sf_dir, "region").join(nations, F.col("r_regionkey") == F.col("n_regionkey"), "left")
    written = regions.select(F.concat_ws(":", F.lit("region"), "r_regionkey").alias("key"), F.to_xml(F.struct("r_regionkey", "r_name", "nation"), {"rowTag": "region"}).alias("xml"))
    return written.unionByName(customers.select(F.concat_ws(":", F.lit("customer"), "c_custkey").alias("key"), F.to_xml(F.struct("c_custkey", "c_nationkey", "order"), {"rowTag": "customer"}).alias("xml")))
