"""Schemas of the relations that the methods exchange."""

from __future__ import annotations

EDGE = "eid long, u long, v long"
VERTEX = "v long, part int"
LEVELLED = "eid long, u long, v long, pu int, pv int, join_level int"
META = "level int, a int, b int, weight long"
TREE = "level int, child_a int, child_b int, parent int, weight long"
PARTMAP = "level int, leaf int, part int"
FRAG = "fid long, level int, part int, ftype string, src long, dst long, n_edges long"
ITEM = "fid long, level int, part int, seq int, off long, item_kind string, item_id long, fwd boolean, a long, b long"
CIRCUIT = "comp long, pos long, eid long, src long, dst long"
LEVELSTAT = "level int, part int, i long, ob long, eb long, local long, remote long"
