"""Pattern queries: model, text dialect, planning, pruning, detection."""
