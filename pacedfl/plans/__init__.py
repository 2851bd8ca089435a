"""Round loop, accounting, sweeps and reports."""
