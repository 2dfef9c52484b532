"""License scans report every notice of a block."""

from fedlake.llm.license_scan import TEMPLATES, Scanner

BSD3 = next(t for name, t in TEMPLATES if name == "BSD-3-Clause")


def names(block):
    return sorted(name for name, _, _ in Scanner().match(block))


def test_numbered_clauses_after_a_reserved_line():
    clauses = BSD3.replace("met: Redistributions", "met:\n1. Redistributions").replace("disclaimer. Redistributions", "disclaimer.\n2. Redistributions").replace("distribution. Neither", "distribution.\n3. Neither")
    assert names(f"Copyright (c) 2020, A. Author\nAll rights reserved.\n\n{clauses}") == ["BSD-3-Clause", "LicenseRef-all-rights-reserved"]


def test_two_reworded_notices():
    gpl = next(t for n, t in TEMPLATES if n == "GPL-3.0-or-later").replace("This program is", "This tool is")
    isc = next(t for n, t in TEMPLATES if n == "ISC").replace("appear in all copies", "appear in every copy")
    assert names(f"{gpl}\n{isc}") == ["GPL-3.0-or-later", "ISC"]


def test_many_short_notices():
    short = ["Released under the MIT License.", "Licensed under CC BY 4.0.", "Licensed under CC BY-NC 4.0.", "Licensed under CC BY-SA 4.0.", "Licensed under the Apache License, Version 2.0.", "All rights reserved."]
    assert names("\n".join(short)) == sorted(n for n, t in TEMPLATES if t in short)
