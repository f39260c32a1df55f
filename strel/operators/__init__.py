"""The methods: functions over space and time, topology, features, relations, tests, baselines."""
