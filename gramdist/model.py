"""Schemas of the tables that operators take and give."""

from __future__ import annotations

STRING = "string_id long, text string"
PAIR = "pair_id long, a_id long, b_id long"
SLP = "string_id long, codec string, size int, length long, depth int, lhs array<int>, rhs array<int>"
RULES = "gid long, var int, kind string, sym int, lhs int, rhs int"
SEGMENT = "string_id long, x int, seg_no int, sym_id int, start long, len int, role string"
DIST = "a_text string, b_text string, p int, q int, payload binary"
RESULT = "pair_id long, distance double"
COUNTED = "pair_id long, distance double, counters map<string,long>"
EVENT = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
