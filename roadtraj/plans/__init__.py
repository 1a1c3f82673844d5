"""Physical helpers: bucketed range joins, size-checked broadcasts, the packed container."""
