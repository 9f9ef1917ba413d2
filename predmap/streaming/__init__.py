"""Maps on streams: enrichment, generations and monitors."""
