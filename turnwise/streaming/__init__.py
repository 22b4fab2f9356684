"""Edge streams: degrees, windows, hot sets and incremental transposition."""
