"""Sources and sinks: graphs carried by tables, edge files, versioned snapshots."""
