"""Schemas of the tables that operators exchange, as DDL strings."""

SERIES_POINT = "series_id string, pos long, x long"
TOKEN = "series_id string, w int, a int, pos long, word string"
GRAMMAR_SYMBOL = "series_id string, w int, a int, rule int, ix int, sym string, is_rule boolean"
RULE_SPAN = "series_id string, w int, a int, rule int, lo_tok long, hi_tok long, lo long, hi long"
DENSITY_RUN = "series_id string, w int, a int, lo long, hi long, d long"
CURVE_RUN = "series_id string, lo long, hi long, de double, kept int"
CANDIDATE = "series_id string, rank int, lo long, hi long, loc long, value double"
# one row for each member and chunk or segment of a long series; binary columns hold one little-endian number, or one word, after the other
PACKED_TOKENS = "series_id string, w int, a int, part long, start long, at binary, word binary"
PACKED_RUNS = "series_id string, w int, a int, seg long, first long, last long, at binary, d binary, total long, squares long, top long"
PACKED_CURVE = "series_id string, seg long, first long, last long, kept int, at binary, de binary"
