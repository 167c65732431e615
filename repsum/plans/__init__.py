"""Plan-level helpers: scratch storage, global ranks, session defaults."""
