"""Mining, bins, bases, baselines and measures."""
