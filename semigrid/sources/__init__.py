"""Table scans, connectors and input generators."""
