"""Edge streams: deduplicated snapshots, windowed private counts, stateful degrees."""
