"""The feature library: templates that become registered features.

SQL features never raise: divisions are guarded, so no record guard is needed in that lane. Each expression has a twin
for DuckDB in TWINS, with the same names, for checks on the raw tables.
"""

from __future__ import annotations

from collections.abc import Callable

from ..model import FeatureSpec, Output

# Stop words by language, in the order that settles ties.
STOP_WORDS = {
    "de": "der die das und ist nicht mit von den ein".split(), "en": "the and of to in is that for it was".split(),
    "es": "el la de que y en los se del las".split(), "fr": "le la les de et des que une est dans".split(),
}


def _words(text: str) -> str:
    return f"filter(split(lower({text}), '\\\\s+'), w -> w <> '')"


def _duck_words(text: str) -> str:
    return f"list_filter(regexp_split_to_array(lower({text}), '\\s+'), lambda w: w <> '')"


def _hits(words: str, language: str, spark: bool) -> str:
    names = ", ".join(f"'{w}'" for w in STOP_WORDS[language])
    return f"size(filter({words}, w -> w in ({names})))" if spark else f"len(list_filter({words}, lambda w: w in ({names})))"


def _language(words: str, spark: bool, hits: dict[str, str] | None = None) -> str:
    hits = hits or {k: _hits(words, k, spark) for k in STOP_WORDS}
    top = f"greatest({', '.join(hits.values())})"
    cases = " ".join(f"when {h} = {top} then '{k}'" for k, h in hits.items())
    return f"case when {top} = 0 then 'und' {cases} end"


# Letters, marks, numbers, blanks and common punctuation; the share of what is left over tells garbage.
ORDINARY = r"[\p{L}\p{M}\p{N} \t\n\r\f.,;:!?()\x22\x27-]"
GARBAGE_SHARE = 0.2


def _garbage_share(text: str, spark: bool) -> str:
    pattern = ORDINARY.replace("\\", "\\\\") + "+" if spark else ORDINARY  # runs of them go at once, what is left is the same
    return f"length(regexp_replace({text}, '{pattern}', ''{'' if spark else ", 'g'"})) / nullif(length({text}), 0)"


ENTITIES = (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&amp;", "&"))


def _plain_html(html: str, spark: bool) -> str:
    flag = "" if spark else ", 'g'"
    x = f"regexp_replace({html}, '(?s)<(script|style)[^>]*>.*?</(script|style)>', ' '{flag})"
    x = f"regexp_replace({x}, '(?s)<[^>]*>', ' '{flag})"
    for entity, sign in ENTITIES:
        x = f"replace({x}, '{entity}', '{sign}')"
    blanks = "'\\\\s+'" if spark else "'\\s+'"
    return f"trim(regexp_replace({x}, {blanks}, ' '{flag}))"


def _ngram_rep(words: str, spark: bool, n: int = 2) -> str:
    if spark:
        grams = f"transform(sequence(0, size({words}) - {n}), i -> concat(" + ", ' ', ".join(f"{words}[i + {k}]" for k in range(n)) + "))"
        return f"case when size({words}) < {n} then 0D else 1 - size(array_distinct({grams})) / (size({words}) - {n - 1}) end"
    grams = f"list_transform(range(1, len({words}) - {n - 2}), lambda i: " + " || ' ' || ".join(f"({words})[i + {k}]" for k in range(n)) + ")"
    return f"case when len({words}) < {n} then 0.0 else 1 - len(list_distinct({grams})) / (len({words}) - {n - 1}) end"


def lets(text: str) -> dict[str, str]:
    """Subexpressions of a text that features share: its words, the stop words among them, these by language, its lines."""
    tag = "".join(c for c in text if c.isalnum())[:12]
    words, stops = f"_words_{tag}", f"_stops_{tag}"
    names = ", ".join(f"'{w}'" for w in dict.fromkeys(w for ws in STOP_WORDS.values() for w in ws))
    return {words: _words(text), stops: f"filter({words}, w -> w in ({names}))"} | {f"_{k}_{tag}": _hits(stops, k, True) for k in STOP_WORDS} | {f"_lines_{tag}": f"split({text}, '\\n')"}


def expressions(text: str, spark: bool = True, bound: dict[str, str] | None = None, words: str | None = None) -> dict[str, tuple[str, str]]:
    """name: (type, expression) of the row-wise text features, for either engine; bound: names of lets to refer to, words: a column of words."""
    w = words or (_words(text) if spark else _duck_words(text))
    hits = None
    if bound:
        w, _, *names, line_name = bound
        hits = dict(zip(STOP_WORDS, names, strict=True))
    g = "" if spark else ", 'g'"
    size = "size" if spark else "len"
    lines = f"split({text}, '\\n')" if spark else f"string_split({text}, chr(10))"
    if bound:
        lines = line_name
    distinct = f"size(array_distinct({lines}))" if spark else f"len(list_distinct({lines}))"
    like = (lambda p: f"{text} rlike '{p}'") if spark else (lambda p: f"regexp_matches({text}, '{p}')")
    digit = "[0-9]+" if spark else "[0-9]"
    # whether there is a match doesn't depend on how far it reaches to either side
    mail = "[a-zA-Z0-9._]@[a-zA-Z0-9]+[.][a-z]" if spark else "[a-zA-Z0-9._]+@[a-zA-Z0-9]+[.][a-z]+"
    urls = f"coalesce(aggregate(regexp_extract_all({text}, '(https?://|www[.])[^ ]+', 0), 0, (a, x) -> a + length(x)), 0)" if spark else f"coalesce(list_sum(list_transform(regexp_extract_all({text}, '(https?://|www[.])[^ ]+', 0), lambda x: length(x))), 0)"
    return {
        "char_len": ("bigint", f"length({text})"),
        "word_count": ("bigint", f"{size}({w})"),
        "lang_guess": ("string", _language(w, spark, hits)),
        "ngram_rep": ("double", _ngram_rep(w, spark)),
        "url_ratio": ("double", f"{urls} / nullif(length({text}), 0)"),
        "digit_ratio": ("double", f"(length({text}) - length(regexp_replace({text}, '{digit}', ''{g}))) / nullif(length({text}), 0)"),
        "garbage_flag": ("boolean", f"({like('%%%')} or {like('[*][*][*]')} or {like('###')} or {like('[$][$][$]')} or contains({text}, '\ufffd') or coalesce({_garbage_share(text, spark)} > {GARBAGE_SHARE}, false))"),
        "content_md5": ("string", f"md5({text})"),
        "line_rep": ("double", f"1 - {distinct} / {size}({lines})"),
        "pii_flag": ("boolean", f"({like(mail)} or {like('[0-9]{3}[- ][0-9]{3,4}')})"),
        "secret_flag": ("boolean", like("(sk|AKIA|ghp)[-_]?[A-Za-z0-9]{12,}")),
        "license_flag": ("boolean", f"({like('[Ll]icensed under')} or {like('All rights reserved')})"),
    }


def needed(expr: str, shared: dict[str, str]) -> list[tuple[str, str]]:
    """The lets that an expression refers to, and what those refer to, in order."""
    wanted: set[str] = set()
    for name in reversed(shared):
        if name in expr or any(name in shared[w] for w in wanted):
            wanted.add(name)
    return [(n, e) for n, e in shared.items() if n in wanted]


TEXT_FEATURES = tuple(expressions("x"))
FUSED_EIGHT = ("char_len", "word_count", "lang_guess", "ngram_rep", "url_ratio", "digit_ratio", "garbage_flag", "content_md5")


def text_feature(name: str, column: str = "processed.plain", source: str = "processed") -> FeatureSpec:
    shared = lets(column)
    kind, expr = expressions(column, bound=shared)[name]
    return FeatureSpec.sql(name, kind, expr, (source,), lets=tuple(needed(expr, shared)))


def model_feature(name: str, kind: str, inputs: tuple[str, ...], mode: str = "all", model_mb: float = 350.0, args: tuple[str, ...] | None = None) -> FeatureSpec:
    """A feature computed by functions.models, over arguments in SQL (by default the inputs, `processed` as its text)."""
    args = args or tuple("processed.plain" if i == "processed" else i for i in inputs)
    return FeatureSpec(name, inputs, (Output(name, kind),), args, fn=name, mode=mode, model_mb=model_mb)


def plain_feature(html: str = "raw.body", source: str = "raw") -> FeatureSpec:
    """Text of a payload: tags go if it begins like markup."""
    expr = f"named_struct('plain', case when {html} like '<%' then {_plain_html(html, True)} else {html} end)"
    return FeatureSpec("plain", (source,), (Output("processed", "struct<plain:string>"),), (expr,))


def domain_feature(url: str = "raw.url", source: str = "raw") -> FeatureSpec:
    """The site that a row comes from: the last two labels of its host, or none."""
    return FeatureSpec.sql("domain_label", "string", f"coalesce(nullif(regexp_extract({url}, '^[a-z]+://(?:[^/:?#]*[.])?([^./:?#]+[.][^./:?#]+)', 1), ''), 'none')", (source,))


def ngram_feature(n: int, column: str = "processed.plain", source: str = "processed") -> FeatureSpec:
    """Share of repeated word n-grams."""
    shared = lets(column)
    return FeatureSpec.sql(f"ngram_rep_{n}", "double", _ngram_rep(next(iter(shared)), True, n), (source,), lets=tuple(needed(next(iter(shared)), shared)))


def token_features(column: str = "processed.plain", source: str = "processed") -> list[FeatureSpec]:
    """Hash tokens and their number, for sample assembly."""
    w = _words(column)
    return [FeatureSpec("tokens", (source,), (Output("tokens", "array<int>"), Output("n_tokens", "int")), (f"transform({w}, w -> cast(pmod(xxhash64(w), 50000) as int))", f"size({w})"))]


def conversation_features() -> list[FeatureSpec]:
    """Features over an array of turns, raw.turns: struct<turn, role, text>."""
    joined = "array_join(transform(raw.turns, t -> coalesce(t.text, '')), '\\n')"
    shared = {k: v for k, v in lets(joined).items()}
    texts = expressions(joined, bound=shared)
    rows = {
        "n_turns": ("int", "size(raw.turns)"),
        "user_share": ("double", "size(filter(raw.turns, t -> t.role = 'user')) / nullif(size(raw.turns), 0)"),
        "has_system": ("boolean", "exists(raw.turns, t -> t.role = 'system')"),
        "avg_reply_len": ("double", "aggregate(filter(raw.turns, t -> t.role = 'assistant'), 0L, (a, t) -> a + length(t.text)) / nullif(size(filter(raw.turns, t -> t.role = 'assistant')), 0)"),
        "alternates": ("boolean", "forall(sequence(1, greatest(size(raw.turns) - 1, 1)), i -> coalesce(raw.turns[i].role <> raw.turns[i - 1].role, true))"),
    } | {k: texts[k] for k in ("char_len", "lang_guess", "digit_ratio", "pii_flag")}
    return [FeatureSpec.sql(k, kind, expr, ("raw",), lets=tuple(needed(expr, shared))) for k, (kind, expr) in rows.items()]


def perplexity_feature(text: str = "processed", language: str = "lang_guess") -> FeatureSpec:
    """Perplexity under character trigrams counted over all rows of the same language."""
    return FeatureSpec("ppl", (text, language), (Output("ppl", "double"),), fn="ppl", scope="table", mode="gpu_only", model_mb=14_000.0)


def safety_feature(weights: str, inputs: tuple[str, ...] = ("processed",), args: tuple[str, ...] | None = None) -> FeatureSpec:
    """A learned score from 0 to 1; weights: what models.train_safety made of labelled texts."""
    from dataclasses import replace

    return replace(model_feature("safety", "double", inputs, "gpu_only", 7000.0, args), hints=(("weights", weights),))


TEMPLATES: dict[str, Callable[..., FeatureSpec]] = {n: (lambda n=n, **k: text_feature(n, **k)) for n in TEXT_FEATURES} | {"plain": plain_feature, "ppl": perplexity_feature, "safety": lambda weights="", **k: safety_feature(weights, **k)}


def template(name: str, **options) -> FeatureSpec:
    """A library feature by name."""
    if name in TEMPLATES:
        return TEMPLATES[name](**options)
    kinds = {"quality": ("double", ("char_len", "word_count", "ngram_rep", "digit_ratio"), "all", 350.0), "math_hit": ("boolean", ("processed", "quality"), "all", 120.0)}
    kind, inputs, mode, mb = kinds[name]
    return model_feature(name, kind, options.get("inputs", inputs), options.get("mode", mode), options.get("model_mb", mb))


def web_features() -> list[FeatureSpec]:
    """The reference subgraph and its neighbours over raw text or HTML."""
    return [plain_feature(), *(text_feature(n) for n in TEXT_FEATURES), template("quality"), template("math_hit")]
