"""DuckDB building blocks for the oracles. Bodies are hex strings; words are numbers up to 8 bytes, bit strings beyond."""

from __future__ import annotations

from basisflow.functions import reed_solomon

DOCUMENTS = "SELECT source AS source_id, doc_id AS packet_id, hex(encode(text)) AS h FROM documents"
PAGES = "SELECT regexp_extract(url, '//([^/:?#]*)', 1) AS source_id, page_id AS packet_id, hex(encode(html)) AS h FROM pages"
CONVERSATIONS = "SELECT conv_id::VARCHAR AS source_id, conv_id * 10000 + turn AS packet_id, hex(encode(text)) AS h FROM conversations"


def byte(value: str) -> str:
    return f"lpad(upper(to_hex(({value})::BIGINT)), 2, '0')"


_HUNDRED = "round({0} * 100)"
RECORDS4 = f"SELECT (l_suppkey % 16)::VARCHAR AS source_id, row_number() OVER () AS packet_id, {byte(_HUNDRED.format('l_discount'))} || {byte(_HUNDRED.format('l_tax'))} || {byte('l_linenumber')} || {byte('ascii(l_returnflag)')} AS h FROM lineitem"
RECORDS8 = f"SELECT (l_suppkey % 16)::VARCHAR AS source_id, row_number() OVER () AS packet_id, {byte('l_quantity')} || {byte(_HUNDRED.format('l_discount'))} || {byte(_HUNDRED.format('l_tax'))} || {byte('l_linenumber')} || {byte('ascii(l_returnflag)')} || {byte('ascii(l_linestatus)')} || '0000' AS h FROM lineitem"


def ship_dates(n_b: int) -> str:
    per = n_b // 2
    return f"""SELECT source_id, packet_id, string_agg(v, '' ORDER BY pos) AS h FROM (
      SELECT l_suppkey::VARCHAR AS source_id, (row_number() OVER w - 1) // {per} AS packet_id, row_number() OVER w AS pos, lpad(upper(to_hex(date_diff('day', DATE '1970-01-01', l_shipdate::DATE)::BIGINT)), 4, '0') AS v
      FROM lineitem WINDOW w AS (PARTITION BY l_suppkey ORDER BY l_shipdate)) GROUP BY source_id, packet_id"""


def uint(value: str, width: int) -> str:
    """Hex of the lowest ``width`` bytes of an integer."""
    return f"right(lpad(upper(to_hex(({value})::BIGINT)), 16, '0'), {2 * width})"


def column(table: str, source: str, order: str, value: str, samples: int) -> str:
    """A column as packets of ``samples`` values (hex) per source, in order."""
    return f"""SELECT source_id, packet_id, string_agg(v, '' ORDER BY pos) AS h FROM (
      SELECT {source}::VARCHAR AS source_id, (row_number() OVER w - 1) // {samples} AS packet_id, row_number() OVER w AS pos, {value} AS v
      FROM {table} WINDOW w AS (PARTITION BY {source} ORDER BY {order})) GROUP BY source_id, packet_id"""


def chunks(payloads: str, n_b: int) -> str:
    """CTE bodies p and c: c has source_id, packet_id, chunk_seq and x (hex of the padded chunk)."""
    w = 2 * n_b
    return f"""p AS ({payloads}),
c AS (SELECT source_id, packet_id, i AS chunk_seq, rpad(substr(h, i * {w} + 1, {w}), {w}, '0') AS x
      FROM p CROSS JOIN LATERAL (SELECT unnest(range(0, (length(h) + {w - 1}) // {w})) AS i))"""


def _number(x: str) -> str:
    return f"('0x' || {x})::UBIGINT"


def prepared(n_b: int, kind: str, width: int) -> str:
    """CTE body c2: c with x after preprocessing."""
    if kind == "none":
        return "c2 AS (SELECT * FROM c)"
    n, w = n_b // width, 2 * width
    sample = f"list_transform(range(0, {n}), lambda i: ('0x' || substr(x, i * {w} + 1, {w}))::BIGINT)"
    if kind == "offset":
        out = "list_transform(s, lambda v: v - list_min(s))"
    else:
        out = f"list_transform(range(1, {n + 1}), lambda i: CASE WHEN i = 1 THEN s[1] ELSE (s[i] - s[i - 1] + {1 << 8 * width}) % {1 << 8 * width} END)"
    return f"c2 AS (SELECT source_id, packet_id, chunk_seq, x AS raw, list_aggregate(list_transform({out}, lambda v: lpad(upper(to_hex(v)), {w}, '0')), 'string_agg', '') AS x FROM (SELECT *, {sample} AS s FROM c))"


def hamming(n_b: int, source: str = "c") -> str:
    """CTE body w: source with syn, spare and word, one word for each basis."""
    if n_b <= 8:
        m = (8 * n_b).bit_length() - 1
        masks = [sum(1 << p for p in range(1 << m) if p >> t & 1) for t in range(m)]
        syn = " + ".join(f"((bit_count((v & {mask}::UBIGINT)::BIT) % 2) << {t})" for t, mask in enumerate(masks))
        return f"w AS (SELECT *, xor(v, 1::UBIGINT << syn::UBIGINT) >> 1 AS word, (v & 1)::BIGINT AS spare FROM (SELECT *, ({syn})::BIGINT AS syn FROM (SELECT *, {_number('x')} AS v FROM {source})))"
    top = 8 * n_b - 1
    syn = f"list_reduce(list_transform(range(1, {top + 1}), lambda p: CASE WHEN get_bit(v, ({top} - p)::INT) = 1 THEN p ELSE 0 END), lambda a, b: xor(a, b))"
    return f"w AS (SELECT *, set_bit(set_bit(v, ({top} - syn)::INT, 1 - get_bit(v, ({top} - syn)::INT)), {top}, 0) AS word, get_bit(v, {top})::BIGINT AS spare FROM (SELECT *, {syn} AS syn FROM (SELECT *, unhex(x)::BIT AS v FROM {source})))"


def rs2(n_b: int, source: str = "c") -> str:
    """CTE body w for two parity symbols: word is the hex of the basis, errs the number of wrong symbols."""
    exp, log = (t.tolist() for t in reed_solomon.tables())
    e = lambda i: f"list_extract({exp[:255]}, ({i}) % 255 + 1)"
    g = lambda v: f"list_extract({[0] + log[1:]}, ({v}) + 1)"
    b = f"list_transform(range(0, {n_b}), lambda i: ('0x' || substr(x, 2 * i + 1, 2))::BIGINT)"
    s1 = f"list_reduce(list_transform(range(0, {n_b}), lambda i: CASE WHEN b[i + 1] = 0 THEN 0 ELSE {e(f'{g("b[i + 1]")} + {n_b - 1} - i')} END), lambda p, q: xor(p, q))"
    place = f"({g('s1')} - {g('s0')} + 255) % 255"
    one = f"s0 > 0 AND s1 > 0 AND place < {n_b}"
    inv = (255 - log[3]) % 255  # 1 + the primitive element is 3
    low = f"CASE WHEN xor(s0, s1) = 0 THEN 0 ELSE {e(f'{g("xor(s0, s1)")} + {inv}')} END"
    fixed = f"CASE WHEN {one} AND place >= 2 THEN substr(x, 1, 2 * ({n_b - 1} - place)) || lpad(upper(to_hex(xor(b[{n_b} - place], s0))), 2, '0') || substr(x, 2 * ({n_b} - place) + 1) ELSE x END"
    return f"""w AS (SELECT *, substr({fixed}, 1, {2 * n_b - 4}) AS word, CASE WHEN s0 = 0 AND s1 = 0 THEN 0 WHEN {one} THEN 1 ELSE (e1 > 0)::INT + (xor(s0, e1) > 0)::INT END AS errs
 FROM (SELECT *, {low} AS e1 FROM (SELECT *, {place} AS place FROM (SELECT *, list_reduce(b, lambda p, q: xor(p, q)) AS s0, {s1} AS s1 FROM (SELECT *, {b} AS b FROM {source})))))"""


def counted(payloads: str, n_b: int, kind: str = "none", width: int = 1, dev: str = "0", transform: str = "hamming") -> str:
    """``WITH`` clause up to k: one row of chunks, exact_bases, bases, dev_sum, q_chunks, q_dev for one fixed deviation length."""
    raw = "x" if kind == "none" else "raw"
    code = {"hamming": lambda: hamming(n_b, "c2"), "rs": lambda: rs2(n_b, "c2"), "identity": lambda: "w AS (SELECT *, x AS word FROM c2)"}[transform]()
    return f"""WITH {chunks(payloads, n_b)}, {prepared(n_b, kind, width)}, {code},
k AS (SELECT count(*) AS chunks, count(DISTINCT {raw}) AS exact_bases, count(DISTINCT word) AS bases, count(*) * {dev} AS dev_sum,
             count(DISTINCT {raw}) - count(DISTINCT word) AS q_chunks, (count(DISTINCT {raw}) - count(DISTINCT word)) * {dev} AS q_dev FROM w)"""


def scheme_rows(n_b: int, k_b: int, h: int) -> str:
    """A row per scheme from k."""
    rows = {"raw": ("chunks", f"chunks * {n_b}"), "exact": ("exact_bases", f"exact_bases * {n_b} + chunks * {h}"), "sim_plain": ("bases", f"bases * {k_b} + chunks * {h} + dev_sum"), "sim_short": ("bases", f"bases * {k_b} + chunks * {h}"), "sim_dual": ("bases", f"bases * {n_b} + q_dev + chunks * {h}")}
    return " UNION ALL ".join(f"SELECT '{s}' AS scheme, chunks, {b} AS bodies, ({t})::BIGINT AS total_bytes, chunks * {n_b} AS original_bytes, chunks * {n_b} / ({t})::DOUBLE AS ratio FROM k" for s, (b, t) in rows.items())


def outcomes(payloads: str, n_b: int, scope: str = "") -> str:
    """``WITH`` clause up to o: chunks with their outcome."""
    by = f"{scope}, " if scope else ""
    return f"""WITH {chunks(payloads, n_b)}, {hamming(n_b)},
o AS (SELECT *, CASE WHEN row_number() OVER (PARTITION BY {by}x ORDER BY packet_id, chunk_seq) > 1 THEN 'repeat'
                     WHEN row_number() OVER (PARTITION BY {by}word ORDER BY packet_id, chunk_seq) = 1 THEN 'new_basis' ELSE 'new_chunk' END AS outcome FROM w)"""
