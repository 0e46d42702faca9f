"""Schemas out and in: Relax NG (compact and XML form) from models; content models from Relax NG, DTD and XSD text."""

from __future__ import annotations

import re
import xml.etree.ElementTree as ET
from xml.sax.saxutils import escape

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqschema.functions.expr import Choice, Concat, Empty, Repeat, Shuffle, Symbol, children, joined, parse_expr, symbols, to_text

NAMESPACE = "http://relaxng.org/ns/structure/1.0"
MARKS = {"?": "optional", "*": "zeroOrMore", "+": "oneOrMore"}


def compact(e, known: set[str]) -> str:
    """A pattern in compact form; symbols without a definition of their own become elements that hold text."""
    if isinstance(e, Empty):
        return "empty"
    if isinstance(e, Symbol):
        return f"e.{e.name}" if e.name in known else f"element {e.name} {{ text }}"
    if isinstance(e, Repeat):
        inner = compact(e.part, known)
        return f"({inner}){e.op}" if children(e.part) else inner + e.op
    mark = {Concat: ", ", Shuffle: " & ", Choice: " | "}[type(e)]
    return mark.join(f"({compact(p, known)})" if isinstance(p, Concat | Shuffle | Choice) else compact(p, known) for p in e.parts)


def xml_pattern(e, known: set[str]) -> str:
    if isinstance(e, Empty):
        return "<empty/>"
    if isinstance(e, Symbol):
        name = escape(e.name, {'"': "&quot;"})
        return f'<ref name="e.{name}"/>' if e.name in known else f'<element name="{name}"><text/></element>'
    tag = MARKS[e.op] if isinstance(e, Repeat) else {Concat: "group", Shuffle: "interleave", Choice: "choice"}[type(e)]
    return f"<{tag}>{''.join(xml_pattern(p, known) for p in children(e))}</{tag}>"


def to_relaxng(models: DataFrame, form: str = "compact") -> DataFrame:
    """(model_key, text): one definition for each model."""
    @F.pandas_udf("array<string>")
    def used(texts: pd.Series) -> pd.Series:
        return pd.Series([sorted(set(symbols(parse_expr(t)))) for t in texts])

    # of a model's symbols, those that have a definition of their own
    own = models.select("model_key", F.explode(used("expr")).alias("sym")).join(models.select(F.col("model_key").alias("sym")).distinct(), "sym", "left_semi")
    names = own.groupBy("model_key").agg(F.collect_set("sym").alias("names"))

    @F.pandas_udf("string")
    def emit(keys: pd.Series, texts: pd.Series, known: pd.Series) -> pd.Series:
        out = []
        for key, text, own in zip(keys, texts, known, strict=True):
            e, own = parse_expr(text), set() if own is None else set(own)
            out.append(f"e.{key} = element {key} {{ {compact(e, own)} }}" if form == "compact" else f'<define xmlns="{NAMESPACE}" name="e.{key}"><element name="{key}">{xml_pattern(e, own)}</element></define>')
        return pd.Series(out)

    return models.join(names, "model_key", "left").select("model_key", emit("model_key", "expr", "names").alias("text"))


def _local(tag: str) -> str:
    return tag.rpartition("}")[2]


def _relaxng(node):
    tag = _local(node.tag)
    parts = [x for x in map(_relaxng, node) if x is not None]
    if tag == "ref":
        return Symbol(re.sub(r"^e\.", "", node.get("name", "")))
    if tag == "element":
        return Symbol(node.get("name", ""))
    if tag in MARKS.values():
        return Repeat(joined(Concat, parts), next(k for k, v in MARKS.items() if v == tag)) if parts else Empty()
    if tag in ("interleave", "choice"):
        return joined(Shuffle if tag == "interleave" else Choice, parts)
    return joined(Concat, parts) if tag == "group" else Empty() if tag == "empty" else None


def _own(name: str) -> str:
    """A name without its prefix."""
    return name.rpartition(":")[2]


def _xsd(node, named: dict, seen: frozenset = frozenset()):
    """named: the schema's complex types and groups by (tag, name). One that holds itself adds nothing the second time."""
    tag, low, high = _local(node.tag), node.get("minOccurs", "1"), node.get("maxOccurs", "1")

    def inside(holder, seen=seen) -> list:
        return [x for x in (_xsd(c, named, seen) for c in holder) if x is not None]

    def of(key) -> list:
        return inside(named[key], seen | {key}) if key in named and key not in seen else []

    if high == "0":
        return None
    if tag == "element":
        e = Symbol(_own(node.get("name") or node.get("ref", "")))
    elif tag in ("sequence", "choice", "all"):
        e = joined({"sequence": Concat, "choice": Choice, "all": Shuffle}[tag], inside(node))
    elif tag == "group":
        parts = of(("group", _own(node.get("ref", ""))))
        if not parts:
            return None
        e = joined(Concat, parts)
    elif tag in ("complexContent", "restriction"):
        e = joined(Concat, inside(node))
    elif tag == "extension":
        e = joined(Concat, of(("complexType", _own(node.get("base", "")))) + inside(node))
    else:
        return None
    op = {("0", "1"): "?", ("1", "1"): ""}.get((low, high), "*" if low == "0" else "+")
    return Repeat(e, op) if op else e


#: Deepest nesting of parameter entities, and the most characters that a text may grow to with them in place.
DEPTH, LONGEST = 20, 10_000_000
ENTITY = re.compile(r"""<!ENTITY\s+%\s+(\S+)\s+(?:"([^"]*)"|'([^']*)')\s*>""")
REFERENCE = re.compile(r"%([\w.:-]+);")


def _expanded(text: str) -> str:
    """A DTD without comments, its own parameter entities put in place; of several values of a name the first counts.
    References that stay (external ones, circles, texts that grow too long) are left as they are."""
    text, values = re.sub(r"<!--.*?-->", "", text, flags=re.S), {}
    for name, double, single in ENTITY.findall(text):
        values.setdefault(name, double or single)
    text = ENTITY.sub("", text)
    for _ in range(DEPTH):
        used = [m for m in REFERENCE.findall(text) if m in values]
        if not used or len(text) + sum(len(values[m]) for m in used) > LONGEST:
            break
        text = REFERENCE.sub(lambda m: f" {values[m[1]]} " if m[1] in values else m[0], text)
    return text


def _dtd(text: str) -> list[tuple[str, str]]:
    found = re.findall(r"<!ELEMENT\s+(\S+)\s+([^>]+)>", _expanded(text))
    every, out = sorted({name for name, _ in found}), []
    for name, body in found:
        if "%" in body:
            continue
        if body.strip() == "ANY":  # any of the elements, any number of times
            out.append((name, to_text(Repeat(joined(Choice, [Symbol(n) for n in every]), "*"))))
            continue
        body = "" if body.strip() == "EMPTY" else re.sub(r"#PCDATA\s*\|?", "", body).replace(",", " ").strip()
        try:
            out.append((name, to_text(parse_expr(re.sub(r"\(\s*\)[*+?]?", "()", body)))))
        except ValueError:
            continue
    return out


def content_models(text: str) -> list[tuple[str, str]]:
    """(element, expression) pairs of a schema text; what cannot be read gives none."""
    if "<!ELEMENT" in text:
        return _dtd(text)
    try:
        root = ET.fromstring(text)
    except ET.ParseError:
        return []
    named, out = {(_local(n.tag), n.get("name")): n for n in root if _local(n.tag) in ("complexType", "group")}, []
    for node in root.iter():
        tag = _local(node.tag)
        if tag == "element" and "relaxng" in node.tag:
            out.append((node.get("name", ""), to_text(joined(Concat, [x for x in map(_relaxng, node) if x is not None]))))
        elif tag == "element" and "XMLSchema" in node.tag and node.get("name"):
            key = ("complexType", _own(node.get("type", "")))
            body, seen = (named[key], frozenset({key})) if key in named else (node.find("{*}complexType"), frozenset())
            if body is not None:
                out.append((node.get("name"), to_text(joined(Concat, [x for x in (_xsd(c, named, seen) for c in body) if x is not None]))))
    return out


def read_content_models(files: DataFrame, text_col: str = "text", source_col: str = "source") -> DataFrame:
    """(source, element, expr) of distinct schema texts."""

    @F.pandas_udf("array<struct<element:string,expr:string>>")
    def read(texts: pd.Series) -> pd.Series:
        return pd.Series([[{"element": a, "expr": b} for a, b in content_models(t or "")] for t in texts])

    return files.select(F.col(source_col).alias("source"), F.col(text_col).alias("_t")).distinct().select("source", F.explode(read("_t")).alias("m")).select("source", "m.element", "m.expr")


__all__ = ["compact", "content_models", "read_content_models", "symbols", "to_relaxng", "xml_pattern"]
