"""Registry of the engine's queries with their SQL, and SQL for the feature frames."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def register(name: str, f: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = f
    if sql:
        ORACLES[name] = sql


def r6(c: Column | str, digits: int = 6) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, digits) + F.lit(0.0)


def rounded(df: DataFrame, *cols: str, digits: int = 6) -> DataFrame:
    return df.withColumns({c: r6(c, digits) for c in cols})


VECTORS = "select vec_id as id, list_transform(embedding, lambda v: cast(v as double)) as v from embeddings"
LINE_KEYS = "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice"
LINES = f"select {LINE_KEYS}, l_quantity as quantity, l_extendedprice as price, l_discount as discount, l_tax as tax from lineitem"
CUSTOMERS = """select c_custkey, c_acctbal as acctbal, coalesce(cast(n as double), 0.0) as n_orders, coalesce(s, 0.0) as sum_price, coalesce(s / n, 0.0) as avg_price,
  coalesce(m, 0.0) as max_price, coalesce(u / cast(n as double), 0.0) as urgent_share
  from customer left join (select o_custkey, count(*) as n, cast(sum(cast(o_totalprice as decimal(18,2))) as double) as s, cast(max(cast(o_totalprice as decimal(18,2))) as double) as m,
    count(*) filter (where o_orderpriority = '1-URGENT') as u from orders group by o_custkey) on c_custkey = o_custkey"""
CUSTOMER_FEATURES = ["acctbal", "n_orders", "sum_price", "avg_price", "max_price", "urgent_share"]
ORDERS = "select o_orderkey, o_totalprice as price, cast(date_diff('day', date '1995-01-01', cast(o_orderdate as date)) as double) as days from orders"
EVENTS = "select event_id, value, cast(hour(ts) as double) as hour, cast(json_extract_string(props, '$.k') as double) as k from events"
PARTS = "select p_partkey, cast(p_size as double) as size, p_retailprice as price from part"
DOCUMENTS = r"""select doc_id, cast(length(t) as double) as chars, cast(len(w) as double) as words, length(t) / cast(greatest(len(w), 1) as double) as mean_word,
  len(regexp_extract_all(t, '[0-9]')) / n as digit_share, len(regexp_extract_all(t, '[A-Z]')) / n as upper_share, len(regexp_extract_all(t, '[.,;:!?]')) / n as punct_share,
  len(list_distinct(w)) / cast(greatest(len(w), 1) as double) as distinct_share, cast(length(t) - length(replace(t, chr(10), '')) + 1 as double) as lines
  from (select doc_id, t, cast(greatest(length(t), 1) as double) as n, list_filter(string_split_regex(t, '[ \t\n\r]+'), lambda x: x <> '') as w from (select doc_id, coalesce(text, '') as t from documents))"""
DOCUMENT_FEATURES = ["chars", "words", "mean_word", "digit_share", "upper_share", "punct_share", "distinct_share", "lines"]
_types = ["click", "view", "purchase", "signup"]
USERS = "select user_id, cast(count(*) as double) as n, avg(value) as mean_value, stddev_pop(value) as sd_value, max(value) as max_value, " + ", ".join(f"count(*) filter (where event_type = '{t}') / cast(count(*) as double) as share_{t}" for t in _types) + " from events group by user_id"
USER_FEATURES = ["n", "mean_value", "sd_value", "max_value", *(f"share_{t}" for t in _types)]
PAGES = r"""select page_id, cast(length(t) as double) as html_len, cast(len(regexp_extract_all(t, '<[a-z]')) as double) as tags, cast(len(regexp_extract_all(t, '<a ')) as double) as links,
  cast(len(regexp_extract_all(t, '<script')) as double) as scripts, length(regexp_replace(t, '<[^>]*>', '', 'g')) / cast(greatest(length(t), 1) as double) as text_share, cast(len(regexp_extract_all(u, '/')) as double) as url_depth
  from (select page_id, coalesce(html, '') as t, coalesce(url, '') as u from pages)"""
PAGE_FEATURES = ["html_len", "tags", "links", "scripts", "text_share", "url_depth"]
CONVERSATIONS = "select conv_id, cast(count(*) as double) as turns, avg(n) as mean_len, cast(max(n) as double) as max_len, stddev_pop(n) as sd_len, count(*) filter (where role = 'user') / cast(count(*) as double) as user_share from (select *, length(coalesce(text, '')) as n from conversations) group by conv_id"
CONVERSATION_FEATURES = ["turns", "mean_len", "max_len", "sd_len", "user_share"]
CUSTOMERS_SCALED = f"""select c_custkey as id, [{', '.join(f'({f} - lo_{f}) / (hi_{f} - lo_{f})' for f in CUSTOMER_FEATURES)}] as v
  from ({CUSTOMERS}), (select {', '.join(f'min({f}) as lo_{f}, max({f}) as hi_{f}' for f in CUSTOMER_FEATURES)} from ({CUSTOMERS}))"""


def dist_sql(metric: str = "euclidean", a: str = "a.v", b: str = "b.v") -> str:
    z = f"list_zip({a}, {b})"
    if metric == "manhattan":
        return f"list_sum(list_transform({z}, lambda z: abs(z[1] - z[2])))"
    if metric == "cosine":
        size = lambda v: f"sqrt(list_sum(list_transform({v}, lambda q: q * q)))"
        return f"1 - list_sum(list_transform({z}, lambda z: z[1] * z[2])) / ({size(a)} * {size(b)})"
    square = f"list_sum(list_transform({z}, lambda z: (z[1] - z[2]) * (z[1] - z[2])))"
    return square if metric == "sqeuclidean" else f"sqrt({square})"


def edges_sql(view: str) -> str:
    """CTEs x and e(i, j, dist)."""
    return f"x as materialized ({view}), e as materialized (select a.id as i, b.id as j, {dist_sql()} as dist from x a join x b on a.id <> b.id)"


def knn_sql(view: str, k: int) -> str:
    """CTEs up to n(i, j, rank, dist)."""
    return f"{edges_sql(view)}, n as materialized (select * from (select *, row_number() over (partition by i order by dist, j) as rank from e) where rank <= {k})"


def cdf_sql(view: str, keys: str, features: list[str]) -> str:
    """CTEs x and t: x plus ul_, ur_ and us_<feature>."""
    skew = lambda f: f"(select avg(pow({f} - m, 3)) / pow(stddev_pop({f}), 3) from (select {f}, avg({f}) over () as m from x))"
    rank = ", ".join(f"count(*) over (order by {f} range between unbounded preceding and current row) / cast(count(*) over () as double) as l_{f}, count(*) over (order by {f} range between current row and unbounded following) / cast(count(*) over () as double) as r_{f}" for f in features)
    tails = ", ".join(f"-ln(l_{f}) as ul_{f}, -ln(r_{f}) as ur_{f}, case when s_{f} < 0 then -ln(l_{f}) else -ln(r_{f}) end as us_{f}" for f in features)
    return f"x as materialized ({view}), s as (select {', '.join(f'{skew(f)} as s_{f}' for f in features)}), l as (select *, {rank} from x), t as (select {keys}, {tails} from l, s)"


def side_sums(features: list[str]) -> str:
    return "greatest(" + ", ".join(" + ".join(f"{u}_{f}" for f in features) for u in ("ul", "ur", "us")) + ")"
