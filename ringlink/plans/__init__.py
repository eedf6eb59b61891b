"""Plan-level helpers: durable intermediate results, size-checked broadcasts, salted joins, executor choice."""
