"""Hand-written rows that both engines get alike."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

CODE = [
    (1, "python", "import os\n\ndef area(w, h):\n    total = w * h\n    if total > 10:\n        return total\n    return 0\n"),
    (2, "python", "class A:\n    def f(self):\n        pass\n    def g(self):\n        pass\n"),
    (3, "python", "import os\nimport sys\nimport re\nfrom . import x\nx = 1\n"),
    (4, "python", "# only a comment\n# and more\n# and more still\n"),
    (5, "c", "#include <stdio.h>\nint main(void) {\n  int i = 0;\nagain:\n  i = i + 1;\n  if (i < 3) goto again;\n  return i;\n}\n"),
    (6, "c", "#define A 1\n#define B 2\n#define C 3\n"),
    (7, "cpp", "#include <vector>\ntemplate <class T>\nT add(T a, T b) {\n  return a + b;\n}\n"),
    (8, "cpp", "class P {\npublic:\nprivate:\nprotected:\n};\n"),
    (9, "csharp", "using System;\nclass P {\n  public int Size { get; set; }\n  static int Twice(int a) {\n    return a * 2;\n  }\n}\n"),
    (10, "csharp", "using A;\nusing B;\n[Serializable]\nclass Q { }\n"),
    (11, "java", "import java.util.List;\nclass A {\n  int size;\n  int twice(int a) {\n    for (int i = 0; i < a; i++) size += i;\n    return size;\n  }\n}\n"),
    (12, "java", "class B {\n  int x;\n  int getX() { return x; }\n  void setX(int v) { x = v; }\n}\n"),
    (13, "javascript", "const a = require('a');\nfunction f(x) {\n  return a(x) + 1;\n}\n"),
    (14, "javascript", "a=1;b=2;c=3;d=4;e=5;f=6;g=7;h=8;i=9;j=10;k=11;console.log(a)"),
    (15, "go", "package main\n\nimport \"fmt\"\n\nfunc main() {\n\tif x, err := g(); err != nil {\n\t\tfmt.Println(x)\n\t}\n}\n"),
    (16, "go", "// Code generated by tool. DO NOT EDIT.\npackage p\n\ntype T struct {\n}\n"),
    (17, "html", "<html><body>\n<p>Some text that a reader sees on the page, and more of it.</p>\n</body></html>\n"),
    (18, "html", "<script>var a = 1;</script>\n<style>p { margin: 0 }</style>\n<i></i><b></b>\n"),
    (19, "c", "/* Copyright 2014-2016 Some Company. All rights reserved. */\nint twice(int a) {\n  return 2 * a;\n}\n"),
    (20, "python", "# Copyright (c) 2020 A. Writer\n# Licensed under the MIT license\n\nx = 3\nprint(x)\n"),
    (21, "java", "// Copyright 2019 Some Company\npackage a;\nclass C { int f() { return 1; } }\n"),
    (22, "python", "0xdeadbeef 0xcafebabe 0x12345678\n0xdeadbeef 0xcafebabe 0x12345678\n"),
    (23, "python", "TODO\nFIXME\nTODO later\n"),
    (24, "c", "int f(int a {\n  return ((a;\n"),
]


def code_files(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(i, lang, text) for i, lang, text in CODE], "file_id long, lang string, text string")


def quoted(text: str) -> str:
    return "'" + text.replace("'", "''").replace("\n", "' || chr(10) || '").replace("\t", "' || chr(9) || '") + "'"


CODE_VALUES = "files as (select file_id::bigint as file_id, lang, text from (select * from (values " + ", ".join(f"({i}, '{lang}', {quoted(text)})" for i, lang, text in CODE) + ") v(file_id, lang, text)) as files_all)"
