"""URL rules whose block decisions reach all aliases of a page (operator 8), in DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from objann.llm.graph import connected_components
from objann.llm.shared import read_table, scratch, written

# Fixed values: (verdict, host, path) of the rules of the query.
RULES = [
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("allow", "net", "/de/"),
    ("block", "example.net", "/de/8"),
    ("block", "org", "/es/"),
]

MAX_RULES = 10_000  # rules are an argument on the driver, not data; more than fit one expression are refused


def host_of(url: Column) -> Column:
    """After the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z in lower case; else empty."""
    rest = _after_scheme(url)
    host = F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1)
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def path_of(url: Column) -> Column:
    """What follows the host up to ``?``, ``#`` or the end; else empty."""
    return F.regexp_extract(_after_scheme(url), r"(?s)^[^/?#]*([^?#]*)", 1)


def _after_scheme(url: Column) -> Column:
    at = F.instr(url, "://")
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))


def best_rule(host: Column, path: Column, rules: list[tuple[str, str, str]]) -> Column:
    """struct(verdict, rule) of the longest fitting rule (host and path together), or null.

    Of two rules of one length the allow goes first, then the smaller text.  The rules are a list
    on the driver, checked against MAX_RULES; they become one expression, with no join.
    """
    if len(rules) > MAX_RULES:
        raise ValueError(f"{len(rules)} rules; at most {MAX_RULES} fit one expression")
    out = F.lit(None).cast("struct<verdict:string,rule:string>")
    ordered = sorted(rules, key=lambda r: (-len(r[1] + r[2]), r[0] != "allow", r[1] + r[2]))
    for verdict, rule_host, rule_path in reversed(ordered):
        fits = ((host == rule_host) | F.endswith(host, F.lit("." + rule_host))) & F.startswith(path, F.lit(rule_path))
        out = F.when(fits, F.struct(F.lit(verdict).alias("verdict"), F.lit(rule_host + rule_path).alias("rule"))).otherwise(out)
    return out


def decoded(text: Column) -> Column:
    """Character references of a URL attribute resolved: all numeric ones, and the named ones of markup."""
    refs = F.array_distinct(F.regexp_extract_all(text, F.lit(r"&#(?:[0-9]{1,7}|[xX][0-9a-fA-F]{1,6})(?:;|(?![0-9a-fA-F]))"), F.lit(0)))

    def resolve(acc: Column, ref: Column) -> Column:
        body = F.regexp_replace(ref, "[&#;]", "")
        code = F.when(body.rlike("^[xX]"), F.conv(F.substring(body, 2, 10), 16, 10)).otherwise(body).cast("long")
        letter = F.decode(F.unhex(F.lpad(F.hex(code), 8, "0")), "UTF-32")
        fine = code.between(1, 1114111) & ~code.between(55296, 57343)
        return F.when(fine, F.replace(acc, ref, letter)).otherwise(acc)

    out = F.when(F.size(refs) > 0, F.aggregate(refs, text, resolve)).otherwise(text)
    for name, letter in (("lt", "<"), ("gt", ">"), ("quot", '"'), ("apos", "'"), ("amp", "&")):
        out = F.replace(out, F.lit(f"&{name};"), F.lit(letter))
    return out


def with_resolved(df: DataFrame, link: str, base: str, into: str) -> DataFrame:
    """``df`` with the absolute URL of a link found on the page ``base``; null for other schemes than ``name://`` and for empty links.

    Absolute, scheme-relative (``//host``), rooted (``/path``), query-only (``?q``) and relative links,
    with ``.`` and ``..`` taken out of the path.  Each step is a column of its own, so that no
    expression is written out more than once.
    """
    l = F.col("__link")  # noqa: E741
    out = df.withColumns(
        {
            "__link": F.trim(link),
            "__scheme": F.regexp_extract(base, r"(?s)^([^:/?#]+:)", 1),
            "__origin": F.regexp_extract(base, r"(?s)^([^:/?#]+://[^/?#]*)", 1),
            "__path": F.regexp_extract(base, r"(?s)^[^:/?#]+://[^/?#]*([^?#]*)", 1),
        }
    ).withColumn("__folder", F.regexp_extract("__path", r"(?s)^(.*/)", 1))
    whole = (
        F.when(l.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*://"), l)
        .when(l.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*:") | (l == "") | (F.col("__origin") == ""), None)
        .when(F.startswith(l, F.lit("//")), F.concat("__scheme", l))
        .when(F.startswith(l, F.lit("/")), F.concat("__origin", l))
        .when(l.rlike("^[?#]"), F.concat("__origin", "__path", l))
        .otherwise(F.concat(F.col("__origin"), F.when(F.col("__folder") == "", "/").otherwise(F.col("__folder")), l))
    )
    parts = r"(?s)^([^:/?#]+://[^/?#]*)([^?#]*)(.*)$"
    out = out.withColumn("__whole", whole).withColumns({f"__part{k}": F.regexp_extract("__whole", parts, k) for k in (1, 2, 3)}).withColumn("__names", F.split("__part2", "/"))
    start = F.expr("cast(array() as array<string>)")
    back = lambda acc: F.when(F.size(acc) > 1, F.slice(acc, 1, F.size(acc) - 1)).otherwise(acc)
    kept = F.aggregate("__names", start, lambda acc, n: F.when(n == ".", acc).when(n == "..", back(acc)).otherwise(F.concat(acc, F.array(n))))
    ends = F.when(F.element_at("__names", -1).isin(".", ".."), "/").otherwise("")
    dotted = F.col("__part2").rlike(r"(?:^|/)\.\.?(?:/|$)")
    out = out.withColumn(into, F.when(dotted, F.concat(F.col("__part1"), F.array_join(kept, "/"), ends, F.col("__part3"))).otherwise(F.col("__whole")))
    return out.drop(*[c for c in out.columns if c.startswith("__")])


def node_of(url: Column) -> Column:
    """The name of a URL among aliases: scheme and host in lower case, no fragment, ``/`` for an empty path."""
    bare = F.regexp_replace(url, "(?s)#.*$", "")
    head, rest = (F.regexp_extract(bare, r"(?s)^([^:/?#]+://[^/?#]*)(.*)$", k) for k in (1, 2))
    return F.when(head == "", url).otherwise(F.concat(F.lower(head), F.when(F.startswith(rest, F.lit("/")), rest).otherwise(F.concat(F.lit("/"), rest))))


def _attribute(tag: Column, name: str) -> Column:
    pattern = rf"""(?is)[\s"'/]{name}\s*+=\s*+(?:"([^"]*+)"|'([^']*+)'|([^\s"'>]++))"""
    return F.concat(*[F.regexp_extract(tag, pattern, k) for k in (1, 2, 3)])


def alias_edges(pages: DataFrame, url: str = "url", html: str = "html") -> DataFrame:
    """(src, dst) URLs that name one page: all canonical links and timed redirects in its html.

    Comments and scripts are left out; attribute values may be quoted or not and hold character
    references; links are resolved against the page's base link or URL.
    """
    whole = F.col(html)
    likely = pages.where(F.col(url).isNotNull() & (whole.ilike("%canonical%") | whole.ilike("%refresh%")))
    clean = F.regexp_replace(whole, r"(?is)<!--.*?(?:-->|\z)|<(script|style|textarea|template)\b.*?(?:</\1\s*>|\z)", " ")
    tags = likely.select(F.col(url).alias("src"), F.regexp_extract_all(clean, F.lit(r"(?is)<(?:link|meta|base)\b[^>]*+>"), F.lit(0)).alias("tags"))
    first_base = F.coalesce(F.try_element_at(F.filter("tags", lambda t: t.rlike(r"(?is)^<base\b")), F.lit(1)), F.lit(""))
    tag = F.col("tag")
    found = tags.select("src", _attribute(first_base, "href").alias("base_link"), F.explode("tags").alias("tag"))
    found = found.select("src", "base_link", *[_attribute(tag, name).alias(name.replace("-", "_")) for name in ("rel", "http-equiv", "href", "content")])
    # written, so that the filters below are not pushed into the expressions above
    found = written(found, "alias-tags")
    target = F.regexp_extract("content", r"""(?is)^[^;,]*[;,]\s*(?:url\s*=\s*)?["']?([^"']*+)""", 1)
    canonical = F.array_contains(F.split(F.lower("rel"), r"\s+"), "canonical") & (F.col("href") != "")
    links = found.select("src", "base_link", F.when(canonical, F.col("href")).when(F.lower(F.trim("http_equiv")) == "refresh", target).alias("link")).where("link IS NOT NULL")
    links = links.select("src", decoded(F.col("base_link")).alias("base_link"), decoded(F.col("link")).alias("link"))
    links = with_resolved(links, "base_link", "src", "base").select("src", "link", F.coalesce("base", "src").alias("base"))
    edges = with_resolved(links, "link", "base", "target").select("src", "target")
    edges = written(edges.select(node_of(F.col("src")).alias("src"), node_of(F.col("target")).alias("dst")), "alias-links")
    return edges.where("dst IS NOT NULL AND dst <> src").distinct()


def _alias_verdicts(edges: DataFrame, rules: list[tuple[str, str, str]]) -> DataFrame | None:
    """(alias, group_verdict) of all URLs whose alias group a rule reaches, as a written table; None without any link."""
    edges = written(edges, "alias-edges")
    if edges.isEmpty():
        return None
    members = written(connected_components(edges, one_task_edges=0), "alias-members")
    own = members.withColumn("own", best_rule(host_of(F.col("node")), path_of(F.col("node")), rules)["verdict"])
    groups = own.groupBy("component").agg(F.when(F.max(F.col("own") == "allow"), "allow").when(F.max(F.col("own") == "block"), "block").alias("group_verdict"))
    return written(members.join(groups, "component").select(F.col("node").alias("alias"), "group_verdict").where("group_verdict IS NOT NULL"), "alias-verdicts", lasting=True)


def judge(pages: DataFrame, rules: list[tuple[str, str, str]] = RULES, key: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """(key, host, path, rule, verdict) of every page.

    A page that a rule fits has that rule's verdict.  Others take the verdict of their alias
    group, which is the connected component of their URL over redirects and canonical links
    (also to URLs that are no page here): allow if a rule allows any member, else block if a rule blocks any,
    else allow.  Null URLs and URLs without ``://`` have an empty host and path and fit no rule; a
    null URL is allowed, another has the verdict of its aliases.  Null html has no links.  Repeated rows repeat; other columns are left out.
    """
    slim = pages.select(F.col(key).alias("key"), F.col(url).cast("string").alias("url"))
    with scratch():
        decided = _alias_verdicts(alias_edges(pages.select(F.col(url).cast("string").alias("url"), F.col(html).cast("string").alias("html"))), rules)
    empty = F.coalesce(F.col("url"), F.lit(""))
    placed = slim.withColumn("host", host_of(empty)).withColumn("path", path_of(empty)).withColumn("best", best_rule(F.col("host"), F.col("path"), rules))
    if decided is None:
        judged = placed.withColumn("group_verdict", F.lit(None).cast("string"))
    else:
        judged = placed.withColumn("alias", node_of(F.col("url"))).join(decided, "alias", "left")
    verdict = F.col("best.verdict")
    return judged.select(F.col("key").alias(key), "host", "path", F.col("best.rule").alias("rule"), F.coalesce(verdict, F.col("group_verdict"), F.lit("allow")).alias("verdict"))


def op8_url_filter(spark, sf_dir: str) -> DataFrame:
    return judge(read_table(spark, sf_dir, "pages"))


def _rule_sql() -> str:
    ordered = sorted(RULES, key=lambda r: (-len(r[1] + r[2]), r[0] != "allow", r[1] + r[2]))
    fits = lambda h, p: f"(host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}')"
    rule = " ".join(f"WHEN {fits(h, p)} THEN '{h}{p}'" for _, h, p in ordered)
    verdict = " ".join(f"WHEN {fits(h, p)} THEN '{v}'" for v, h, p in ordered)
    return f"CASE {rule} END AS rule, CASE {verdict} ELSE 'allow' END AS verdict"


OP8_SQL = f"""
WITH u AS (
  SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages
), h AS (
  SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u
)
SELECT page_id, host, path, {_rule_sql()} FROM h
"""
