"""The selector's operators: windows, attention scores, selection, baselines and measures."""
