"""Sources and sinks: chat records, round trips through formats, manifests."""
