"""Where execution logs and query sets come from."""
