"""Where grids come from: tables, raw files, formulas, archives."""
