"""Learners over arrays: they train inside executor tasks, one task per candidate and fold, on the shared reduced set."""
