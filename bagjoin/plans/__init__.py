"""Driver-side planning: decompositions, covers, measures and strategies. Metadata only, never rows."""
