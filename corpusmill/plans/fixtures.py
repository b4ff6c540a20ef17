"""Derived inputs: one SQL text that Spark and DuckDB evaluate alike on the given tables.

In the texts below ~ stands for a backslash and ` for a line feed.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..sources.tables import load


def _literal(text: str) -> str:
    return "replace(replace('" + text.replace("'", "''") + "', '~', chr(92)), '`', chr(10))"


def _cases(on: str, plants: dict[int, str], otherwise: str = "''") -> str:
    return f"case {on} " + " ".join(f"when {k} then {_literal(v)}" for k, v in plants.items()) + f" else {otherwise} end"


CODE = {
    0: "<pre><code>def add(a, b):`    total = add(a, b)`    return total</code></pre>",
    1: "<p>Set <code>x = 5</code> first.</p>",
    2: "<p>The <code>plain words</code> here.</p>",
    3: "<table><tbody><code>x = f(1);</code><code>y = g(x);</code></tbody></table>",
    4: "<pre>plain prose in a block</pre>",
    5: '<div aria-hidden="true"><code>hidden = f(1)</code></div>',
    6: '<div style="display:none"><code>hidden = f(1)</code></div><p><code>shown = f(2)</code></p>',
    7: '<span style="visibility: hidden">secret prose</span>',
    8: "<pre><code>1`a = f(1)`2`b = f(2)`3`c = f(3)`4`d = f(4)</code></pre>",
    9: "<pre><code>10`11`12`13`14`a = 1`b = 2`77`c = 3`d = 4`e = 5</code></pre>",
    10: "<pre><code>a = f(1)</code></pre><pre><code>b = f(2)</code></pre>",
}
MATH = {
    0: '<script type="math/tex">~frac{a}{b}</script>',
    1: '<script type="math/tex; mode=display">~sum_{i} x_i</script>',
    2: '<script type="math/tex">~frac{a}{b</script>',
    3: '<math><semantics><mi>x</mi><annotation encoding="application/x-tex">x^2</annotation></semantics></math>',
    4: "<math><mi>x</mi><mo>+</mo><mi>y</mi></math>",
    5: '<span class="math-formula">~sqrt{x}</span>',
    6: '<script type="math/asciimath">sum_(i=1)^n i</script>',
    7: '<p><img alt="~alpha + 1" src="a.png"><script type="math/tex">~alpha + 1</script></p>',
    8: '<link rel="stylesheet" href="katex.min.css">',
    9: '<script type="math/tex">~begin{matrix} a ~end{cases}</script>',
    10: "<p>plain ~frac only</p>",
}
ASCII = {
    0: "`~frac ~mu ~log ~sqrt ~sum",
    1: "`~mu ~mu ~mu ~mu ~mu",
    2: "`~frac ~mu ~log ~sqrt",
    3: "`sum log sqrt + *",
}
#: Snippets for the tests of code and of line numbers.
SNIPPETS = [
    "def add(a, b):`    return a", "two words", "x = 5", "print(x)", "a -> b", "nothing here at all", "if (a == b) {", "const y = 3;",
    "1`a`2`b`3`c", "10`11`12`x", "1`x`2`y", "5`7`9", "import os", "the result is good", "#include <a.h>", "1`2`3`4", "7`a`8`b`9",
]


def code_sql() -> str:
    url = "case page_id % 48 when 0 then url || '/diff.php?id=' || cast(page_id as varchar(20)) when 12 then url || '/blame.php?id=' || cast(page_id as varchar(20)) else url end"
    return f"select page_id, {url} as url, replace(html, '</article>', {_cases('page_id % 12', CODE)} || '</article>') as html from pages"


def math_sql() -> str:
    return f"select page_id, url, replace(html, '</article>', {_cases('page_id % 12', MATH)} || '</article>') as html from pages"


def ascii_sql() -> str:
    return f"select doc_id, text || {_cases('doc_id % 10', ASCII)} as text from documents"


def snippets_sql() -> str:
    """A snippet for every page: a planted one, by page_id, above the page's title."""
    title = "coalesce(regexp_extract(html, '<title>([^<]*)</title>', 1), '')"
    return f"select page_id as snippet_id, {_cases(f'page_id % {len(SNIPPETS)}', dict(enumerate(SNIPPETS)))} || chr(10) || {title} as text from pages"


def chain_sql() -> str:
    """Band rows of texts: of eight ids in a row, two chains that meet in their middle member, and two members of their source's giant bucket."""
    base = "select doc_id, doc_id % 8 as m, cast(cast(floor(doc_id / 8) as bigint) as varchar(20)) as g, coalesce(source, '') as source from documents where length(text) > 0"
    rows = ((0, "'k' || g", "1, 7"), (1, "'k' || g", "7, 2"), (0, "'l' || g", "3, 4"), (1, "'l' || g", "4, 5"), (0, "'giant' || source", "0, 6"))
    return " union all ".join(f"select doc_id, {band} as band, {key} as key from ({base}) b where m in ({members})" for band, key, members in rows)


def qa_sql(engine: str) -> str:
    """Conversations as documents; five classes of prefixes."""
    line = (
        "case when conv_id % 5 = 0 then (case role when 'user' then 'Question: ' else 'Answer: ' end) || text "
        "when conv_id % 5 = 1 and role = 'user' then 'Question: ' || text when conv_id % 5 = 2 and role = 'assistant' then 'Answer: ' || text "
        "when conv_id % 5 = 3 then 'data: x what ' || text when conv_id % 5 = 4 then 'Q&A ' || text else text end"
    )
    joined = (
        "array_join(transform(array_sort(collect_list(struct(turn, line))), x -> x.line), chr(10))" if engine == "spark" else "string_agg(line, chr(10) order by turn, line)"
    )
    return f"select conv_id as doc_id, {joined} as text from (select conv_id, turn, {line} as line from conversations where role <> 'system') t group by conv_id"


CHOICE_MARKS = {
    0: ("a. ", "b. ", "c. ", "d. "), 1: ("1) ", "2) ", "3) ", ""), 2: ("i] ", "ii] ", "iii] ", "iv] "), 3: ("A - ", "B - ", "C - ", ""),
    4: ("a. ", "c. ", "d. ", ""), 5: ("a> ", "b> ", "", ""), 6: ("a) ", "b) ", "c) ", ""), 7: ("a. ", "b. ", "", ""),
}
CHOICE_ANSWER = {0: "answer: b", 1: "Ans: 2`explanation: it follows", 2: "solution: i", 4: "answer: a", 6: "reply: a", 7: "answer: a"}


def choice_sql(engine: str) -> str:
    """One document per conversation: a lead, a stem, options from the first turn's words, an answer."""
    words = "split(text, ' ')" if engine == "spark" else "string_split(text, ' ')"
    part = (lambda a, n: f"array_join(slice(w, {a}, {n}), ' ')") if engine == "spark" else (lambda a, n: f"array_to_string(w[{a}:{a + n - 1}], ' ')")
    mark = lambda i: _cases("m", {k: v[i] for k, v in CHOICE_MARKS.items() if v[i]}, "null")
    option = lambda i: f"coalesce(chr(10) || {mark(i)} || 'opt{i} ' || {part(9 + 2 * i, 2)}, '')"
    options = " || ".join(option(i) for i in range(4))
    answer = f"coalesce(chr(10) || {_cases('m', CHOICE_ANSWER, 'null')}, '')"
    stem = f"(case m when 6 then '12. ' else '' end) || 'stem ' || {part(1, 6)}"
    one = f"({stem} || {options} || {answer})"
    text = f"'a lead line' || chr(10) || (case m when 5 then 'answer: a' || chr(10) else '' end) || {one} || (case m when 7 then chr(10) || {one} else '' end)"
    least = "min_by(text, turn)" if engine == "spark" else "arg_min(text, turn)"
    return (
        f"select doc_id, {text} as text from (select conv_id as doc_id, conv_id % 8 as m, {words} as w "
        f"from (select conv_id, replace({least}, chr(10), ' ') as text from conversations where role = 'user' group by conv_id) s) t"
    )


def derived(spark: SparkSession, sf_dir: str, sql: str) -> DataFrame:
    """A fixture on the tables it names."""
    names = [n for n in ("pages", "documents", "conversations", "events") if f"from {n}" in sql]
    # Spark keeps backslashes of literals out of the texts: they are made by chr(92).
    if not names:
        return spark.sql(sql)
    sql = sql.replace("{", "{{").replace("}", "}}")
    for n in names:
        sql = sql.replace(f"from {n}", f"from {{{n}}}")
    return spark.sql(sql, **{n: load(spark, sf_dir, n) for n in names})
