"""Gold SQL in the dialect of file databases, put into Spark's."""

from __future__ import annotations

from xlsql.localize.sql_tree import tokenize

# Functions that differ only by name.
RENAMED = {"iif": "if", "ifnull": "coalesce", "substr": "substring", "julianday": "unix_date", "total": "sum", "char_length": "length", "random": "rand"}
CODES = {"%Y": "yyyy", "%m": "MM", "%d": "dd", "%H": "HH", "%M": "mm", "%S": "ss"}


def to_spark(sql: str) -> str:
    """Rename functions, turn strftime into date_format, ``LIMIT a, b`` into ``LIMIT b OFFSET a``, double-quoted names into back-ticked ones."""
    tokens = tokenize(sql)
    code = [i for i, t in enumerate(tokens) if t.kind != "blank"]
    for n, i in enumerate(code):
        t = tokens[i]
        follows = tokens[code[n + 1]].text if n + 1 < len(code) else ""
        if t.kind == "text" and t.text[0] == '"':
            t.new = "`" + t.text[1:-1] + "`"
        elif t.low in RENAMED and follows == "(":
            t.new = RENAMED[t.low]
        elif t.low == "julianday" and follows == "(":
            t.new = "unix_date"
        elif t.low == "strftime" and follows == "(" and n + 4 < len(code):
            form = tokens[code[n + 2]]
            close, depth = n + 2, 1
            while depth and close + 1 < len(code):
                close += 1
                depth += {"(": 1, ")": -1}.get(tokens[code[close]].text, 0)
            text = form.text
            for k, v in CODES.items():
                text = text.replace(k, v)
            t.new, form.new, tokens[code[n + 3]].new = "date_format", "", ""
            tokens[code[close]].new = f", {text})"
        elif t.low == "limit" and n + 3 < len(code) and tokens[code[n + 2]].text == ",":
            a, b = tokens[code[n + 1]], tokens[code[n + 3]]
            a.new, b.new, tokens[code[n + 2]].new = b.text, a.text, " OFFSET"
    return "".join(t.new if t.new is not None else t.text for t in tokens)
