"""Physical helpers: lineage cuts, ranks without a global window, plan inspection."""
