"""Sources and sinks: tables, request files, derived relations, workload generators."""
