"""Sources and sinks: point views over tables, files, the versioned index store."""
