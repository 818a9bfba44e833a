"""Physical side: lineage cuts, selection, exchange and plan inspection."""
