"""Sources, sinks and incidence builders."""
