"""The methods: probe sets, scorers, curves, mining, corpora, audits, comparisons."""
