"""Part of the block-sketching engine."""
