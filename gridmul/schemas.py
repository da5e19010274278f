"""Schemas of the frames, as DDL; none of them is inferred."""

from __future__ import annotations

ENTRIES = "row long, col long, value long"
ENTRIES_DOUBLE = "row long, col long, value double"
BLOCKS = "block_row int, block_col int, n_rows int, n_cols int, data array<double>"
PLATFORMS = "platform string, alpha double, beta double, gamma double, n long, p long, b long"
RUNS = "method string, grid string, groups long, n long, b long, outer_b long, repeat int, wall_ms double, shuffle_bytes long, shuffle_rows long, spill_bytes long"
